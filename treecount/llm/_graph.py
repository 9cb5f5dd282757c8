"""Connected components by randomised contraction, as joins and aggregations only.

Each round every vertex points to the closed neighbour of least random priority; the edges are
rewritten to those representatives.  The expected number of vertices falls by a constant factor a
round, whatever the shape of the graph (a path needs logarithmically many rounds, a star one), and
no vertex's neighbours ever meet in one task: the choice is an aggregation with map-side combining.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import forget, scratch, written


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(id, component) of every vertex of ``edges``; component is the least id of its component.

    Loops, repeats and null ends are ignored; an empty input gives an empty table.
    """
    with scratch(edges.sparkSession) as keep:
        return keep(_components(edges, a, b))


def _components(edges: DataFrame, a: str, b: str) -> DataFrame:
    e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b")
    e = written(e.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    maps: list[DataFrame] = []
    while not e.isEmpty():
        k = F.lit(len(maps))
        both = e.select(F.col("a").alias("v"), F.col("b").alias("u")).union(e.select(F.col("b").alias("v"), F.col("a").alias("u")))
        first = both.groupBy("v").agg(F.min(F.struct(F.xxhash64("u", k).alias("p"), F.col("u").alias("u"))).alias("m"))
        own = F.struct(F.xxhash64("v", k).alias("p"), F.col("v").alias("u"))
        m = written(first.select("v", F.least("m", own)["u"].alias("r")), "reps")
        maps.append(m)
        n = e.join(m.select(F.col("v").alias("a"), F.col("r").alias("ra")), "a").select("ra", "b")
        n = n.join(m.select(F.col("v").alias("b"), F.col("r").alias("rb")), "b").where("ra <> rb")
        n = written(n.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(), "edges")
        forget(e)
        e = n
    if not maps:
        return written(e.select(F.col("a").alias("id"), F.col("b").alias("component")), "components")
    label = maps[0]
    for m in maps[1:]:
        step = m.select(F.col("v").alias("r"), F.col("r").alias("s"))
        label = label.join(step, "r", "left").select("v", F.coalesce("s", "r").alias("r"))
    least = label.groupBy("r").agg(F.min("v").alias("component"))
    return written(label.join(least, "r").select(F.col("v").alias("id"), "component"), "components")
