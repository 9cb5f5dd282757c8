"""Training-data operators: archives, deduplication, privacy, tokens, quality, packing, scoring.

Nothing outside this subpackage imports it.
"""
