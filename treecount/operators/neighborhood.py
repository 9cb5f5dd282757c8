"""Neighbourhoods of a graph: adjacency, degrees and their summaries, and comparisons of graphs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import EdgeGraph
from .blocks import two_hop_counts
from .exact import degrees
from .exchange import stored, written


def kind_of(v: str = "v"):
    """The entity kind in a vertex id."""
    return F.pmod(F.col(v), F.lit(16)).cast("int")


def adjacency(graph: EdgeGraph) -> DataFrame:
    """(v, nbrs): sorted neighbours.  One array a vertex: for graphs whose largest degree fits a row; hubs belong in tasks."""
    return graph.edges.groupBy(F.col("src").alias("v")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def from_adjacency(lists: DataFrame) -> DataFrame:
    """(v, pos, u): the lists taken apart again, with places from 0."""
    return lists.select("v", F.posexplode("nbrs").alias("pos", "u"))


def orient(graph: EdgeGraph) -> DataFrame:
    """Each edge once, from the end of smaller (degree, id): no vertex keeps a long list."""
    d = degrees(graph)
    e = graph.edges.where("src < dst")
    e = e.join(d.select(F.col("v").alias("src"), F.col("deg").alias("ds")), "src").join(d.select(F.col("v").alias("dst"), F.col("deg").alias("dd")), "dst")
    up = F.col("ds") <= F.col("dd")  # src < dst breaks ties
    return e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("dst"))


def color_edges(graph: EdgeGraph, coloring: DataFrame) -> DataFrame:
    """Edges with the colour masks of both ends."""
    c = coloring.select("v", "mask")
    e = graph.edges.join(c.select(F.col("v").alias("src"), F.col("mask").alias("src_mask")), "src")
    return e.join(c.select(F.col("v").alias("dst"), F.col("mask").alias("dst_mask")), "dst").select("src", "dst", "src_mask", "dst_mask")


def degrees_of(graph: EdgeGraph, vertices: DataFrame) -> DataFrame:
    """Degree of every given vertex, 0 for isolated ones."""
    return vertices.join(degrees(graph), "v", "left").select("v", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))


def isolated(graph: EdgeGraph, vertices: DataFrame) -> DataFrame:
    """Given vertices without an edge."""
    return vertices.join(graph.edges.select(F.col("src").alias("v")), "v", "left_anti")


def diff(one: DataFrame, two: DataFrame) -> DataFrame:
    """(a, b, in_one, in_two): pairs of either table with flags."""
    x, y = one.distinct().withColumn("p", F.lit(1)), two.distinct().withColumn("q", F.lit(1))
    return x.join(y, ["a", "b"], "full").select("a", "b", F.col("p").isNotNull().cast("int").alias("in_one"), F.col("q").isNotNull().cast("int").alias("in_two"))


def subsets_of_color(coloring: DataFrame, k: int) -> DataFrame:
    """(v, sub): every colour subset that holds the vertex's colour; 2^k subsets are broadcast."""
    subs = F.broadcast(coloring.sparkSession.range(1, 1 << k).select(F.col("id").cast("int").alias("sub")))
    return coloring.join(subs, F.expr("(mask & sub) <> 0")).select("v", "sub")


def disjoint_masks(sums: DataFrame) -> DataFrame:
    """(v, m1, m2): pairs of disjoint colour sets that meet at a vertex."""
    x, y = sums.select("v", F.col("mask").alias("m1")), sums.select(F.col("v").alias("w"), F.col("mask").alias("m2"))
    return x.join(y, (F.col("v") == F.col("w")) & F.expr("(m1 & m2) = 0")).select("v", "m1", "m2")


def two_hop_error(graph: EdgeGraph, rsd: float = 0.02) -> DataFrame:
    """(vertices, mean_error): distinct two-hop neighbours by sketch against the exact number.

    A vertex unites its neighbours' sketches, which hold the vertex itself too; the pairs of both ends are not listed.
    """
    graph = stored(graph)
    size = max(4, math.ceil(2 * math.log2(1.04 / rsd)))
    one = written(graph.edges.groupBy(F.col("src").alias("dst")).agg(F.hll_sketch_agg("dst", size).alias("s")), "sketches")
    a = graph.edges.repartition("src").join(one, "dst").groupBy("src").agg((F.hll_sketch_estimate(F.hll_union_agg("s")) - 1).alias("a"))
    n = a.join(two_hop_counts(graph.edges), "src")
    return n.agg(F.count("*").alias("vertices"), F.avg(F.abs(F.col("a") - F.col("n")) / F.col("n")).alias("mean_error"))


def degree_quantiles(graph: EdgeGraph) -> DataFrame:
    q = lambda p: F.expr(f"percentile(deg, {p})")
    return degrees(graph).agg(F.round(q(0.5), 6).alias("median"), F.round(q(0.9), 6).alias("p90"), F.max("deg").alias("max_deg"))


def rank_degree(graph: EdgeGraph) -> DataFrame:
    """Rank, dense rank and row number of each vertex among those of its kind."""
    d = degrees(graph).withColumn("kind", kind_of())
    w = Window.partitionBy("kind").orderBy(F.desc("deg"))
    return d.select("v", "deg", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dense"), F.row_number().over(Window.partitionBy("kind").orderBy(F.desc("deg"), "v")).alias("rn"))


def top_hubs(graph: EdgeGraph, n: int = 3) -> DataFrame:
    """The n largest degrees of each kind, ties by id."""
    w = Window.partitionBy("kind").orderBy(F.desc("deg"), "v")
    return degrees(graph).withColumn("kind", kind_of()).withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= n).select("kind", "rn", "v", "deg")


def common_vertices(one: EdgeGraph, two: EdgeGraph, least: int = 20) -> DataFrame:
    """Vertices of the first graph whose degree in the second is at least ``least``."""
    return one.nodes().select("v").intersect(degrees(two).where(F.col("deg") >= least).select("v"))


def kind_profile(graph: EdgeGraph, kinds: dict[str, int]) -> DataFrame:
    """(v, one column for each kind): neighbour counts by kind, gathered as a map and read back."""
    n = graph.edges.select(F.col("src").alias("v"), kind_of("dst").alias("kind")).groupBy("v", "kind").agg(F.count("*").alias("n"))
    m = n.groupBy("v").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))  # 16 kinds at most
    return m.select("v", *[F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0)).cast("long").alias(name) for name, k in kinds.items()])
