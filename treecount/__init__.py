"""Approximate counting of tree subgraphs on Spark."""

__version__ = "0.1.0"
