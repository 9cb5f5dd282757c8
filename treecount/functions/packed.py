"""The packed layout of counts: one array of C(k, t) numbers a vertex, in ascending order of the colour masks.

For dense tables it saves the mask and the row of every count; combinations are vector products over
the batch's vertices.  Numbers are doubles: exact below 2^53, within about k^2 * 2^-53 beyond.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def masks(k: int, t: int) -> list[int]:
    """Colour sets of t of k colours, ascending; a set's place is its rank."""
    return [m for m in range(1 << k) if m.bit_count() == t]


def pack(counts: DataFrame, k: int, t: int, value: str = "cnt") -> DataFrame:
    """(it, v, cnt array<double>) of rows (it, v, mask, value)."""
    gathered = counts.groupBy("it", "v").agg(F.map_from_entries(F.collect_list(F.struct("mask", F.col(value).cast("double").alias("x")))).alias("m"))
    return gathered.select("it", "v", F.array(*[F.coalesce(F.try_element_at("m", F.lit(m)), F.lit(0.0)) for m in masks(k, t)]).alias("cnt"))


def unpack(packed: DataFrame, k: int, t: int) -> DataFrame:
    """(it, v, mask, cnt double) without zeros."""
    ranks = F.array(*[F.lit(m) for m in masks(k, t)])
    x = packed.select("it", "v", F.posexplode("cnt").alias("rank", "cnt")).where("cnt <> 0")
    return x.select("it", "v", F.get(ranks, F.col("rank")).alias("mask"), "cnt")


def split_ranks(k: int, t: int, a: int):
    """Arrays (r1, r2, starts): ranks of all splits of the sets of t in order of the sets, and where each set's begin."""
    import numpy as np

    r1 = {m: i for i, m in enumerate(masks(k, a))}
    r2 = {m: i for i, m in enumerate(masks(k, t - a))}
    left, right, starts = [], [], []
    for target in masks(k, t):
        starts.append(len(left))
        sub = target
        while sub:
            if sub in r1:
                left.append(r1[sub])
                right.append(r2[target & ~sub])
            sub = (sub - 1) & target
    return np.array(left), np.array(right), np.array(starts)


def combine(keep: DataFrame, sums: DataFrame, d: int, k: int, t: int, a: int) -> DataFrame:
    """Packed counts of the whole from packed kept counts and packed neighbour sums."""
    both = keep.select("it", "v", F.col("cnt").alias("x")).join(sums.select("it", "v", F.col("cnt").alias("y")), ["it", "v"])
    columns = 1 << 18  # numbers of a block of products

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        left, right, starts = split_ranks(k, t, a)
        per = len(left) // len(starts)  # every set has equally many splits
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            x, y = (batch.column(c).flatten().to_numpy(zero_copy_only=False).reshape(n, -1) for c in ("x", "y"))
            out = np.empty((n, len(starts)))
            wide = max(1, columns // (per * n))
            for lo in range(0, len(starts), wide):
                hi = min(lo + wide, len(starts))
                part = slice(lo * per, hi * per)
                out[:, lo:hi] = (x[:, left[part]] * y[:, right[part]]).reshape(n, hi - lo, per).sum(2)
            out /= d
            yield pa.RecordBatch.from_arrays([batch.column("it"), batch.column("v"), pa.array(list(out), pa.list_(pa.float64()))], ["it", "v", "cnt"])

    return both.mapInArrow(run, "it int, v long, cnt array<double>")


def neighbor_sums(cut: DataFrame, edges: DataFrame, k: int, t: int) -> DataFrame:
    """Packed neighbour sums: the arrays are added element by element, each as a column of one aggregation where they are short."""
    width = len(masks(k, t))
    c = cut.select("it", F.col("v").alias("dst"), "cnt")
    j = edges.select("src", "dst").join(c, "dst")
    if width <= 100:
        s = j.groupBy("it", F.col("src").alias("v")).agg(*[F.sum(F.get("cnt", F.lit(i))).alias(f"s{i}") for i in range(width)])
        return s.select("it", "v", F.array(*[f"s{i}" for i in range(width)]).alias("cnt"))
    flat = j.select("it", F.col("src").alias("v"), F.posexplode("cnt").alias("rank", "x")).where("x <> 0").groupBy("it", "v", "rank").agg(F.sum("x").alias("x"))
    m = flat.groupBy("it", "v").agg(F.map_from_entries(F.collect_list(F.struct("rank", "x"))).alias("m"))
    return m.select("it", "v", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("cnt"))
