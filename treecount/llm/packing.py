"""Packing by minimum bin slack.

A document's ids are cut into full windows and one remainder.  Only the multiset of remainder lengths
matters for the plan, and it has fewer distinct lengths than the window has ids, whatever the corpus.
The planner fixes the longest remainder, finds by a bitset subset-sum over the counted lengths the
multiset that fills the rest of the window closest, walks back how many of each length it took, and
uses that filling as often as the counts allow.  Each round exhausts or nearly exhausts a length, so
the plan has a few thousand rows at most.

Pieces learn their place without meeting: a task numbers its remainders of each length, prefix sums
over tasks turn this into a rank, and a binary search in the plan turns length and rank into window
and offset.

Defined cases: null and empty texts are the end id alone; repeated rows and rows that share a doc_id, or
have none, are packed each; pieces of equal length are alike, so ties change nothing; a very long text is cut
into as many windows as it fills; an empty table gives no piece.  Only doc_id and text are read, so other
columns may have any name.  Windows that are not full are padded by the reader; `padding` counts it.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._store import small_batches, written
from .tokens import END_ID, encoder, word_tokenizer

WINDOW = 2048
PIECE = "doc_id long, start long, length int, doc_tokens long, part int, rank long, ids binary"


def fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of lengths, within their counts, whose sum is the largest that is at most ``room``."""
    mask, reach = (1 << (room + 1)) - 1, 1
    steps: list[tuple[int, int, int]] = []  # length, how many at once, sums reached before
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, lot = min(counts[length], room // length), 1
        while left > 0 and not reach >> room & 1:
            lot = min(lot, left)
            steps.append((length, lot, reach))
            reach |= (reach << length * lot) & mask
            left, lot = left - lot, lot * 2
        if reach >> room & 1:
            break
    at, out = reach.bit_length() - 1, {}
    for length, lot, before in reversed(steps):
        if not before >> at & 1:
            out[length] = out.get(length, 0) + lot
            at -= length * lot
    return out


def plan(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[int, dict[int, int]]]:
    """[(times, {length: count})]: fillings that use every remainder exactly once."""
    left, out = {k: n for k, n in histogram.items() if n > 0 and k > 0}, []
    while left:
        longest = max(left)
        left[longest] -= 1
        take = fill({k: n for k, n in left.items() if n > 0}, window - longest)
        left[longest] += 1
        take[longest] = take.get(longest, 0) + 1
        times = min(left[k] // n for k, n in take.items())
        for k, n in take.items():
            left[k] -= n * times
            if not left[k]:
                del left[k]
        out.append((times, take))
    return out


def placements(steps: list[tuple[int, dict[int, int]]]) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Rows (length, first rank, count in a window, first window, offset) by length and rank, and the number of windows."""
    rows, used, window = [], {}, 0
    for times, take in steps:
        offset = 0
        for length in sorted(take, reverse=True):
            first = used.get(length, 0)
            rows.append((length, first, take[length], window, offset))
            used[length] = first + times * take[length]
            offset += length * take[length]
        window += times
    return sorted(rows), window


def padding(steps: list[tuple[int, dict[int, int]]], window: int = WINDOW) -> int:
    return sum(times * (window - sum(k * n for k, n in take.items())) for times, take in steps)


def cut(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """Pieces of every document, at most ``window`` ids each, ranked by length within their task."""
    path = tokenizer or word_tokenizer()
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        enc, part, ranks = encoder(path), TaskContext.get().partitionId(), {}
        kind = "<u2" if enc.width == 2 else "<u4"
        for batch in batches:
            rows = []
            for doc, raw in zip(batch.column("doc_id").to_pylist(), enc.encode(batch.column("text"))):
                ids = np.append(np.frombuffer(raw, kind).astype("<u4"), np.uint32(end_id)).astype("<u4")
                for at in range(0, len(ids), window):
                    piece = ids[at : at + window]
                    n = len(piece)
                    rank = ranks.get(n, 0)
                    ranks[n] = rank + 1
                    rows.append((doc, at, n, len(ids), part, rank, piece.tobytes()))
            cols = list(zip(*rows)) or [()] * 7
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["doc_id", "start", "length", "doc_tokens", "part", "rank", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECE)


def pack(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """(doc_id, start, length, doc_tokens, ids, sequence_id, offset) of every piece."""
    pieces = written(cut(docs, tokenizer, window, end_id), "pieces")
    # one row for each task and length; then at most `window` rows reach the driver
    local = written(pieces.groupBy("part", "length").agg(F.count("*").alias("n")), "piece-counts")
    histogram = {r["length"]: r["n"] for r in local.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    rows, _ = placements(plan(histogram, window))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    local = local.select("part", "length", F.coalesce(before, F.lit(0)).alias("before"))
    # the rows of one (part, length) are those of one task at most, and the other side is one row
    placed = pieces.select("doc_id", "start", "length", "doc_tokens", "part", "rank", F.col("ids")).join(local, ["part", "length"])
    firsts: dict[int, list[tuple[int, int, int, int]]] = {}
    for length, *rest in rows:
        firsts.setdefault(length, []).append(tuple(rest))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        table = {k: np.array(v, np.int64).T for k, v in firsts.items()}
        for batch in batches:
            length = batch.column("length").to_numpy().astype(np.int64)
            rank = batch.column("rank").to_numpy() + batch.column("before").to_numpy()
            seq, off = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for n in np.unique(length):
                at = np.flatnonzero(length == n)
                first, count, window0, offset = table[int(n)]
                step = np.searchsorted(first, rank[at], "right") - 1
                inside = rank[at] - first[step]
                seq[at] = window0[step] + inside // count[step]
                off[at] = offset[step] + inside % count[step] * n
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("start"), pa.array(length), batch.column("doc_tokens"), batch.column("ids"), pa.array(seq), pa.array(off)],
                ["doc_id", "start", "length", "doc_tokens", "ids", "sequence_id", "offset"],
            )

    return placed.mapInArrow(place, "doc_id long, start long, length long, doc_tokens long, ids binary, sequence_id long, offset long")


def op6_min_slack_packing(spark, sf_dir: str) -> DataFrame:
    """All documents packed into windows of 2048 ids."""
    out = pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
