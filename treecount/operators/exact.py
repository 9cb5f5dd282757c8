"""Exact counts: joins, closed forms, and the signed-subset identity."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.templates import TreeTemplate
from ..sources.graphs import EdgeGraph
from . import blocks
from .exchange import forget, narrowed, release, stored, written


def degrees(graph: EdgeGraph) -> DataFrame:
    return graph.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))


def exact_by_joins(graph: EdgeGraph, template: TreeTemplate) -> DataFrame:
    """(exact): one join for each template edge, all vertices different, over the symmetries.

    The path of four grows with the cube of the degrees: its middle edge is joined with both ends' neighbour lists,
    whose pairs are counted, less those of one common vertex, and not listed.
    """
    e = graph.edges
    if template.k == 1:
        return graph.nodes().agg(F.count("*").alias("exact"))
    if template.k == 4 and template.automorphisms == 2:
        return exact_path4(graph)
    part = e.select(F.col("src").alias("v0"), F.col("dst").alias("v1"))
    for p, i in template.edges[1:]:
        part = part.join(e.select(F.col("src").alias(f"v{p}"), F.col("dst").alias(f"v{i}")), f"v{p}")
        for q in range(i):
            if q != p:
                part = part.where(F.col(f"v{q}") != F.col(f"v{i}"))
    return part.agg(F.expr(f"cast(count(*) div {template.automorphisms} as bigint)").alias("exact"))


def exact_star(graph: EdgeGraph, k: int) -> DataFrame:
    """Stars with k vertices: the sum of C(degree, k - 1); both ends count for k = 2.  Long where that fits, decimal beyond."""
    c = F.lit(1).cast("decimal(38,0)")
    for i in range(k - 1):
        c = F.expr(f"cast(deg - {i} as decimal(20,0))") if i == 0 else (c * F.expr(f"cast(deg - {i} as decimal(9,0))")).cast("decimal(38,0)")
    n = degrees(graph).where(F.col("deg") >= k - 1).agg(F.sum(c.cast("decimal(38,0)")).alias("s"))
    whole = n.select((F.coalesce("s", F.lit(0)) / (math.factorial(k - 1) * (2 if k == 2 else 1))).cast("decimal(38,0)").alias("exact"))
    return narrowed(written(whole, "stars"), "exact")


def exact_path3(graph: EdgeGraph) -> DataFrame:
    return exact_star(graph, 3)


def triangles(graph: EdgeGraph) -> DataFrame:
    """(triangles): every edge compares the neighbour lists of its ends in a task that holds both."""
    return blocks.open_ends_and_triangles(graph.edges.where("src < dst")).select("triangles")


def four_cycles(graph: EdgeGraph) -> DataFrame:
    """(cycles): cycles of four vertices, each at its highest vertex in (degree, id), so a hub's pairs are not all listed."""
    table = stored(graph)
    numbered = written(blocks.ranked(table), "ranked")
    if table is not graph:
        forget(table.edges)
    return blocks.four_cycles_of(numbered, last=True)


def exact_path4(graph: EdgeGraph) -> DataFrame:
    """Paths of four vertices: each edge's open ends less three for each triangle."""
    return blocks.open_ends_and_triangles(graph.edges).select((F.col("ends") - 3 * F.col("triangles")).cast("long").alias("exact"))


def exact_path5(graph: EdgeGraph) -> DataFrame:
    """Paths of five vertices, without listing them.

    Around a middle vertex, two neighbours and one further neighbour of each: less those where a further
    neighbour is the other neighbour (triangles) or both are the same vertex (cycles of four).  Both are found in
    the tasks that hold the lists of two vertex blocks; no pairs of neighbours are listed.
    """
    table = stored(graph)
    d = written(degrees(table), "degrees")
    e = table.edges.join(d.select(F.col("v").alias("dst"), F.col("deg").alias("dd")), "dst")
    wide = lambda c: F.sum(c.cast("decimal(38,0)")).cast("decimal(38,0)")
    ends = e.groupBy("src").agg(F.sum(F.col("dd") - 1).cast("decimal(19,0)").alias("s"), F.sum((F.col("dd") - 1) * (F.col("dd") - 1)).cast("decimal(38,0)").alias("q"))
    p = written(ends.agg(F.coalesce(wide((F.col("s") * F.col("s")).cast("decimal(38,0)") - F.col("q")), F.lit(0)).alias("p")), "ends")
    forget(d)
    release(table.edges.sparkSession)
    numbered = written(blocks.ranked(table), "ranked")
    if table is not graph:
        forget(table.edges)
    less = blocks.four_cycles_of(numbered, last=True, triangles=True)
    whole = p.join(less, F.lit(True)).select(((F.col("p") - F.col("around")) / 2 - 4 * F.col("cycles")).cast("decimal(38,0)").alias("exact"))
    return narrowed(written(whole, "paths"), "exact")


def signed_subset_count(graph: EdgeGraph, template: TreeTemplate, coloring: DataFrame) -> DataFrame:
    """(it, colorful): inclusion and exclusion over colour subsets of homomorphism counts; no colour sets are kept.

    A homomorphism of a tree into the vertices coloured from a subset is a product of neighbour sums,
    bottom-up, so each subset needs one number for each vertex.
    """
    k, spark = template.k, graph.edges.sparkSession
    subsets = F.broadcast(spark.range(1, 1 << k).select(F.col("id").cast("int").alias("sub")))  # 2^k rows, k <= 15
    base = coloring.join(subsets, F.expr("(mask & sub) <> 0")).select("it", "sub", "v")

    def hom(node: int) -> DataFrame:
        out = base.withColumn("h", F.lit(1).cast("decimal(38,0)"))
        for child in (i for p, i in template.edges if p == node):
            x = hom(child).select("it", "sub", F.col("v").alias("dst"), F.col("h").alias("x"))
            s = graph.edges.join(x, "dst").groupBy("it", "sub", F.col("src").alias("v")).agg(F.sum("x").cast("decimal(38,0)").alias("x"))
            out = out.join(s, ["it", "sub", "v"]).select("it", "sub", "v", (F.col("h") * F.col("x")).cast("decimal(38,0)").alias("h"))
        return out

    sign = F.when(F.expr(f"({k} - bit_count(sub)) % 2 = 0"), F.col("h")).otherwise(-F.col("h"))
    total = hom(0).groupBy("it").agg(F.sum(sign).alias("s"))
    return total.select("it", F.expr(f"s div {template.automorphisms}").alias("colorful"))
