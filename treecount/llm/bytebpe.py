"""Byte-level BPE in length-bucketed numpy matrices, and its inverse.

Distinct pre-tokens of a batch are sorted into buckets of like length; a bucket is a padded matrix of
ids, one row a pre-token.  In each round every row finds its pair of least rank (the leftmost among
equals) by a lookup in an open-addressing table of pairs, merges it and closes the gap; rows without
a pair leave.  A batch therefore takes as many rounds as its longest pre-token has merges, whatever
its number of rows.  Pre-tokens longer than ``LONG`` bytes are merged alone by a heap.

Texts are cut with the pattern of the vocabulary.  With the default pattern, between two other characters a single space or line
break always begins a match, so such texts are cut there first and the ids of each chunk are kept in a
bounded memo.

Defined cases: null texts are empty; empty texts have no ids; lone surrogates cannot occur in a Spark
string; repeated rows and rows that share a doc_id, or have none, are encoded each; pairs of equal rank are
merged from the left; a very long text is one row of a batch of bounded rows; an empty table gives an empty
result.  Only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import base64
import heapq
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import small_batches

LONG = 512
MEMO = 500_000
_CODECS: dict[tuple[str, str], Codec] = {}


def multi_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


class PairTable:
    """(left id, right id) -> rank of the merged token, as a hash table in arrays."""

    def __init__(self, pairs: dict[tuple[int, int], int]):
        import numpy as np

        size = 1 << max(4, (4 * len(pairs)).bit_length())
        self.bits = size.bit_length() - 1
        self.keys, self.ranks = np.full(size, -1, np.int64), np.full(size, np.iinfo(np.int32).max, np.int32)
        self.depth = 1
        for (a, b), rank in pairs.items():
            key, step = a << 32 | b, 0
            at = self._slot(key)
            while self.keys[at] != -1:
                at, step = (at + 1) & (size - 1), step + 1
            self.keys[at], self.ranks[at], self.depth = key, rank, max(self.depth, step + 1)

    def _slot(self, key: int) -> int:
        return (key * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF) >> (64 - self.bits)

    def rank(self, left, right):
        """Ranks of arrays of pairs; the largest 32-bit integer where there is none."""
        import numpy as np

        key = left.astype(np.int64) << 32 | right
        with np.errstate(over="ignore"):
            at = (key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)
        out = np.where(self.keys[at] == key, self.ranks[at], np.iinfo(np.int32).max)
        open_ = np.flatnonzero((self.keys[at] != key) & (self.keys[at] != -1))
        for _ in range(self.depth - 1):
            if not len(open_):
                break
            at[open_] = (at[open_] + 1) & (len(self.keys) - 1)
            found = self.keys[at[open_]] == key[open_]
            out[open_[found]] = self.ranks[at[open_[found]]]
            open_ = open_[~found & (self.keys[at[open_]] != -1)]
        return out


class Codec:
    """Encoder and decoder of one vocabulary of ranks and one splitting pattern."""

    def __init__(self, path: str, pattern: str):
        import numpy as np
        import regex

        with open(path, "rb") as f:
            self.ids = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.find = regex.compile(pattern).findall
        self.known = pattern == default_pattern()
        self.byte = np.array([self.ids[bytes([i])] for i in range(256)], np.int64)
        pairs = {}
        for token, rank in self.ids.items():
            for cut in range(1, len(token)):
                a, b = self.ids.get(token[:cut]), self.ids.get(token[cut:])
                if a is not None and b is not None:
                    pairs[a, b] = rank
        self.pairs, self.table = pairs, PairTable(pairs)
        top = max(self.ids.values()) + 1
        words = [b""] * top
        for token, rank in self.ids.items():
            words[rank] = token
        self.words = words
        self.memo: dict[str, bytes] = {}

    # -- encoding -------------------------------------------------------------------------------

    def merge(self, tokens: list[bytes]) -> list[bytes]:
        """Ids of each distinct pre-token as little-endian unsigned 32-bit integers."""
        import numpy as np

        out: list[bytes] = [b""] * len(tokens)
        buckets: dict[int, list[int]] = {}
        for i, t in enumerate(tokens):
            whole = self.ids.get(t)
            if whole is not None:
                out[i] = whole.to_bytes(4, "little")
            elif len(t) > LONG:
                out[i] = np.array(self._heap(t), "<u4").tobytes()
            else:
                buckets.setdefault((len(t) + 3) // 4 * 4, []).append(i)
        for width, rows in buckets.items():
            lot = max(1, (1 << 20) // width)
            for k in range(0, len(rows), lot):
                part = rows[k : k + lot]
                for i, ids in zip(part, self._matrix([tokens[i] for i in part], width)):
                    out[i] = ids
        return out

    def _matrix(self, tokens: list[bytes], width: int) -> list[bytes]:
        import numpy as np

        n = len(tokens)
        none = np.iinfo(np.int32).max
        raw = np.frombuffer(b"".join(t.ljust(width, b"\0") for t in tokens), np.uint8).reshape(n, width)
        size = np.array([len(t) for t in tokens])
        m = self.byte[raw]
        col = np.arange(width)
        ranks = np.full((n, width), none, np.int32)
        left, right = m[:, :-1], m[:, 1:]
        real = col[1:] < size[:, None]
        ranks[:, :-1][real] = self.table.rank(left[real], right[real])
        live = np.arange(n)
        while len(live):
            sub = ranks[live]
            at = sub.argmin(1)
            best = sub[np.arange(len(live)), at]
            go = best != none
            live, at, best = live[go], at[go], best[go]
            if not len(live):
                break
            # close the gap right of each merged place
            src = np.minimum(col + (col > at[:, None]), width - 1)
            m[live] = np.take_along_axis(m[live], src, 1)
            ranks[live] = np.take_along_axis(ranks[live], src, 1)
            size[live] -= 1
            m[live, at] = best
            ranks[live, size[live] - 1] = none
            for shift in (0, -1):  # the pair that begins at the merged token, and the one before
                p = at + shift
                ok = (p >= 0) & (p + 1 < size[live])
                rows, cols = live[ok], p[ok]
                ranks[rows, cols] = self.table.rank(m[rows, cols], m[rows, cols + 1])
        return [m[i, : size[i]].astype("<u4").tobytes() for i in range(n)]

    def _heap(self, token: bytes) -> list[int]:
        ids = [int(self.byte[b]) for b in token]
        n = len(ids)
        nxt, prv = [*range(1, n), -1], [-1, *range(n - 1)]
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.pairs.get((ids[i], ids[i + 1]))) is not None]
        heapq.heapify(heap)
        alive = [True] * n
        while heap:
            rank, i, a, b = heapq.heappop(heap)
            j = nxt[i]
            if not alive[i] or j < 0 or ids[i] != a or ids[j] != b:
                continue
            ids[i], alive[j], nxt[i] = rank, False, nxt[j]
            if nxt[i] >= 0:
                prv[nxt[i]] = i
            for x in (prv[i], i):
                y = nxt[x] if x >= 0 else -1
                if x >= 0 and y >= 0 and (r := self.pairs.get((ids[x], ids[y]))) is not None:
                    heapq.heappush(heap, (r, x, ids[x], ids[y]))
        return [ids[i] for i in range(n) if alive[i]]

    def chunks(self, text: str) -> list[str]:
        """Parts of a text that the pattern matches independently of each other; the whole text for a pattern we know nothing about."""
        if not self.known:
            return [text]
        if "\0" in text or "  " in text or " \n" in text or "\n " in text or "\n\n" in text or text[:1].isspace() or text[-1:].isspace() or not _OTHER_SPACE.isdisjoint(text):
            return [text] if len(text) <= LONG else self.find(text)
        return text.replace(" ", "\0 ").replace("\n", "\0\n\0").split("\0")

    def encode(self, texts: list[str | None]) -> list[bytes]:
        parts = [self.chunks(t) if t else [] for t in texts]
        memo = self.memo
        new = {x for p in parts for x in p if x not in memo}
        if len(memo) + len(new) > MEMO:
            memo.clear()
            new = {x for p in parts for x in p}
        if new:
            new = list(new)
            split = [self.find(x) for x in new]
            known: dict[str, int] = {}
            for s in split:
                for t in s:
                    known.setdefault(t, len(known))
            ids = self.merge([t.encode("utf-8") for t in known])
            for x, s in zip(new, split):
                memo[x] = b"".join([ids[known[t]] for t in s])
        return [b"".join([memo[x] for x in p]) for p in parts]

    # -- decoding -------------------------------------------------------------------------------

    def decode(self, ids: bytes) -> bytes:
        import numpy as np

        words = self.words
        return b"".join([words[i] for i in np.frombuffer(ids, "<u4").tolist()])


_OTHER_SPACE = frozenset(chr(c) for c in (9, 11, 12, 13, 28, 29, 30, 31, 133, 160, 5760, *range(8192, 8203), 8232, 8233, 8239, 8287, 12288))


def codec(path: str, pattern: str) -> Codec:
    """One codec a worker process; its memo outlives a task."""
    if (path, pattern) not in _CODECS:
        _CODECS[path, pattern] = Codec(path, pattern)
    return _CODECS[path, pattern]


def encode(docs: DataFrame, path: str | None = None, pattern: str | None = None, text: str = "text") -> DataFrame:
    """(doc_id, ids): ids are little-endian unsigned 32-bit integers."""
    path, pattern = path or multi_ranks(), pattern or default_pattern()
    small_batches(docs.sparkSession, 256)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(c.encode(batch.column("text").to_pylist()), pa.binary())], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, ids binary")


def decode(coded: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """(doc_id, ids, raw): the bytes the ids stand for."""
    path, pattern = path or multi_ranks(), pattern or default_pattern()
    small_batches(coded.sparkSession, 256)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            raw = [c.decode(x) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("ids"), pa.array(raw, pa.binary())], ["doc_id", "ids", "raw"])

    return coded.select("doc_id", "ids").mapInArrow(run, "doc_id long, ids binary, raw binary")


def op7_byte_bpe(spark, sf_dir: str) -> DataFrame:
    """Ids of all documents and the bytes decoded from them."""
    out = decode(encode(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    return out.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("raw", 256).alias("decoded_sha256"))
