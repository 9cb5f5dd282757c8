"""Documents scored by masked pseudo-likelihood with a bidirectional window network.

Every word is masked in turn and predicted from the ``SIDE`` words on each side of it: embeddings by
position add up to a hidden layer, a rectifier, and a softmax in three levels.  The network gives the
group of classes, then the class within its group, each as a softmax over ``WIDTH`` outputs given the
context; the word's share of its class, from counts over the whole corpus, gives the word itself.  A
document's score is the sum of the log-probabilities of all its words.

The vocabulary is all words of the corpus: the most frequent have a class of their own, the others
share classes by a hash of their last letters.  The shares are a table that grows with the corpus and is
joined by the word; it never reaches the driver.  Training takes every position of every document in
each of ``ROUNDS`` passes.  Documents are dealt to replicas by a hash of their content, as many as the
corpus's length asks for, and each replica learns from a common start in the order of that hash, so the
result does not depend on how the input is split.  Replicas are averaged with their numbers of examples
as weights by an aggregation over parameter blocks; only the averaged parameters, whose size is fixed,
reach the driver.

Defined cases: null and wordless texts have no word and score 0; repeated rows score alike, as do rows
without a doc_id; an empty table trains nothing and returns nothing; a word at an end of the text sees an
edge class there; ties in the frequency of words go by word order; a very long text is one row of a
batch of bounded rows and is learnt and scored in blocks of positions.  Only doc_id and text are read, so
other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import small_batches, written
from .quality import words

#: Groups of classes, and classes in a group.
WIDTH = 32
SHARED = 128
EDGE = WIDTH * WIDTH - 1
TOP = EDGE - SHARED
CLASSES = WIDTH * WIDTH
SIDE = 2
HIDDEN = 16
ROUNDS = 1
RATE = 0.2
BATCH = 4096
BLOCK = 512
#: Code points of a replica's documents.
REPLICA = 16_000_000


def word_counts(docs: DataFrame) -> DataFrame:
    """(w, count) of all lower-cased words of all documents, as a table."""
    w = docs.select(F.explode(words(F.lower(F.coalesce(F.col("text"), F.lit(""))))).alias("w"))
    return written(w.groupBy("w").count(), "word-counts")


def vocabulary(docs: DataFrame, top: int = TOP, counts: DataFrame | None = None) -> list[str]:
    """The most frequent lower-cased words of all documents; ties in word order."""
    counts = word_counts(docs) if counts is None else counts
    return [r["w"] for r in counts.orderBy(F.desc("count"), "w").limit(top).collect()]


class Net:
    """The window network in numpy; parameters are one float32 vector."""

    def __init__(self, params=None, seed: int = 7):
        import numpy as np

        sizes = (2 * SIDE * CLASSES * HIDDEN, HIDDEN, HIDDEN * WIDTH, WIDTH, WIDTH * HIDDEN * WIDTH, WIDTH * WIDTH)
        if params is None:
            rng = np.random.default_rng(seed)
            params = np.concatenate([rng.normal(0, s, n) for s, n in zip((0.3, 0.0, 0.1, 0.0, 0.1, 0.0), sizes)]).astype(np.float32)
        self.params = np.array(params, np.float32)
        self.views = self._views(self.params, sizes)
        # of each parameter, the squares of its gradients so far
        self.seen = self._views(np.full(len(self.params), 1e-6, np.float32), sizes)

    @staticmethod
    def _views(flat, sizes):
        import numpy as np

        cut = np.cumsum((0, *sizes))
        e, b, g, gp, c, cp = (flat[x:y] for x, y in zip(cut[:-1], cut[1:]))
        return e.reshape(2 * SIDE, CLASSES, HIDDEN), b, g.reshape(HIDDEN, WIDTH), gp, c.reshape(WIDTH, HIDDEN, WIDTH), cp.reshape(WIDTH, WIDTH)

    def _hidden(self, context):
        embed, bias = self.views[:2]
        h = embed[0][context[0]] + bias
        for k in range(1, 2 * SIDE):
            h += embed[k][context[k]]
        return h

    @staticmethod
    def _softmax(z):
        import numpy as np

        z -= z.max(1, keepdims=True)
        np.exp(z, out=z)
        z /= z.sum(1, keepdims=True)
        return z

    def _by_group(self, target):
        """Order of the examples by the target's group, and (group, slice) of those present."""
        import numpy as np

        group = target // WIDTH
        order = np.argsort(group, kind="stable")
        ends = np.cumsum(np.bincount(group, minlength=WIDTH))
        return order, [(g, slice(lo, hi)) for g, (lo, hi) in enumerate(zip(np.concatenate([[0], ends[:-1]]), ends)) if hi > lo]

    def log_probabilities(self, context, target):
        """Of each target class given its context (2 * SIDE arrays)."""
        import numpy as np

        _, _, group, group_prior, inner, inner_prior = self.views
        out = np.empty(len(target), np.float32)
        for i in range(0, len(target), 8192):
            t = target[i : i + 8192]
            order, parts = self._by_group(t)
            t = t[order]
            a = np.maximum(self._hidden([c[i : i + 8192][order] for c in context]), 0)
            p = self._softmax(a @ group + group_prior)[np.arange(len(t)), t // WIDTH]
            for g, part in parts:
                own = t[part] % WIDTH
                p[part] *= self._softmax(a[part] @ inner[g] + inner_prior[g])[np.arange(len(own)), own]
            out[i + order] = np.log(np.maximum(p, 1e-30))
        return out

    def _step(self, k: int, gradient, rate: float, at=...) -> None:
        import numpy as np

        seen = self.seen[k][at]
        seen += gradient * gradient
        self.seen[k][at] = seen
        self.views[k][at] -= rate * gradient / np.sqrt(seen)

    def learn(self, context, target, rate: float) -> None:
        """One pass of gradient descent over the examples, with a rate of each parameter's own."""
        import numpy as np

        _, _, group, group_prior, inner, inner_prior = self.views
        for i in range(0, len(target), BATCH):
            t = target[i : i + BATCH]
            order, parts = self._by_group(t)
            t = t[order]
            near = [c[i : i + BATCH][order] for c in context]
            h = self._hidden(near)
            a = np.maximum(h, 0)
            z = self._softmax(a @ group + group_prior)
            z[np.arange(len(t)), t // WIDTH] -= 1
            back = z @ group.T
            for g, part in parts:
                own = t[part] % WIDTH
                y = self._softmax(a[part] @ inner[g] + inner_prior[g])
                y[np.arange(len(own)), own] -= 1
                back[part] += y @ inner[g].T
                y /= len(t)
                self._step(4, a[part].T @ y, rate, g)
                self._step(5, y.sum(0), rate, g)
            z /= len(t)
            self._step(2, a.T @ z, rate)
            self._step(3, z.sum(0), rate)
            back *= h > 0
            back /= len(t)
            self._step(1, back.sum(0), rate)
            columns = np.ascontiguousarray(back.T)
            for k in range(2 * SIDE):
                sums = np.stack([np.bincount(near[k], x, CLASSES) for x in columns], 1).astype(np.float32)
                self._step(0, sums, rate, k)


class Classes:
    """Class numbers of words."""

    def __init__(self, top: list[str]):
        self.memo = {w.encode(): i for i, w in enumerate(top)}
        self.fixed = dict(self.memo)

    def of(self, text: str | None):
        import zlib

        import numpy as np

        memo = self.memo
        if len(memo) > 300_000:
            memo = self.memo = dict(self.fixed)
        out = []
        for w in (text or "").lower().encode("utf-8", "surrogatepass").split():
            c = memo.get(w)
            if c is None:
                c = memo[w] = TOP + zlib.crc32(w.strip(b".,;:!?")[-4:]) % SHARED
            out.append(c)
        return np.array(out, np.int64)


def windows(ids: list):
    """Contexts and targets of all positions of some documents, and where each document begins."""
    import numpy as np

    gap = np.full(SIDE, EDGE, np.int64)
    flat = np.concatenate([gap, *[x for d in ids for x in (d, gap)]])
    sizes = np.array([len(d) for d in ids])
    starts = np.concatenate([[0], np.cumsum(sizes)])
    at = np.arange(starts[-1]) + SIDE + np.repeat(np.arange(len(ids)) * SIDE, sizes)
    return [flat[at + k] for k in (*range(-SIDE, 0), *range(1, SIDE + 1))], flat[at], starts


def train(docs: DataFrame, top: list[str], rounds: int = ROUNDS, rate: float = RATE, replica: int = REPLICA):
    """Averaged parameters (numpy float32); None where there is no word."""
    import numpy as np

    small_batches(docs.sparkSession)
    params = Net().params
    length = docs.agg(F.sum(F.char_length("text")).alias("n")).first()["n"] or 0
    own = F.xxhash64("text")
    dealt = docs.where("text is not null").select(own.alias("at"), "text").repartition(-(-length // replica) or 1, "at").sortWithinPartitions("at").select("text")
    for turn in range(rounds):
        start, step = params, rate / (1 + turn)

        def run(batches: Iterator[pa.RecordBatch], start=start, step=step) -> Iterator[pa.RecordBatch]:
            import numpy as np

            net, classes, n = Net(start), Classes(top), 0
            for batch in batches:
                ids = [x for t in batch.column("text").to_pylist() if len(x := classes.of(t))]
                if not ids:
                    continue
                context, target, _ = windows(ids)
                net.learn(context, target, step)
                n += len(target)
            if n:
                rows = range(0, len(net.params), BLOCK)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(range(len(rows)), pa.int32()), pa.array([n] * len(rows), pa.int64()), pa.array([net.params[i : i + BLOCK].astype(np.float64) * n for i in rows], pa.list_(pa.float64()))],
                    ["block", "n", "w"],
                )

        rows = _summed(dealt.mapInArrow(run, "block int, n long, w array<double>")).collect()  # a row a parameter
        if not rows:
            return None
        total = max(r["n"] for r in rows)
        params = np.zeros(len(params), np.float32)
        for r in rows:
            params[r["block"] * BLOCK + r["i"]] = r["w"] / total
    return params


def _summed(parts: DataFrame) -> DataFrame:
    """(block, i, n, w): sums over the replicas of each parameter; as many rows as the network has parameters."""
    d = parts.select("block", "n", F.posexplode("w").alias("i", "w"))
    return d.groupBy("block", "i").agg(F.sum("n").alias("n"), F.sum("w").alias("w"))


def score(docs: DataFrame, top: list[str], params) -> DataFrame:
    """(doc_id, n_words, log_likelihood) of the words' classes; `shares` has the rest."""
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(None).cast("long").alias("row"), "text")
    return _class_scores(d, top, params).drop("row")


def _class_scores(docs: DataFrame, top: list[str], params) -> DataFrame:
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        net, classes = Net(params), Classes(top)
        for batch in batches:
            ids = [classes.of(t) for t in batch.column("text").to_pylist()]
            out = np.zeros(len(ids))
            if any(len(x) for x in ids):
                context, target, starts = windows(ids)
                sums = np.concatenate([[0.0], np.cumsum(net.log_probabilities(context, target).astype(np.float64))])
                out = sums[starts[1:]] - sums[starts[:-1]]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("row"), pa.array([len(x) for x in ids], pa.int64()), pa.array(out, pa.float64())], ["doc_id", "row", "n_words", "log_likelihood"])

    return docs.mapInArrow(run, "doc_id long, row long, n_words long, log_likelihood double")


def shares(docs: DataFrame, top: list[str], counts: DataFrame) -> DataFrame:
    """(row, share): the sum of log P(word | class) over a row's words without a class of their own; docs: (row, text), counts of `word_counts`."""
    rare = ~F.col("w").isin(top) if top else F.lit(True)
    w = docs.select("row", F.explode(words(F.coalesce(F.col("text"), F.lit("")))).alias("w")).where(rare)
    ending = F.substring(F.encode(F.btrim("w", F.lit(".,;:!?")), "UTF-8"), -4, 4)
    n = counts.where(rare).select(F.xxhash64("w").alias("h"), F.pmod(F.crc32(ending), F.lit(SHARED)).alias("c"), "count")
    size = n.groupBy("c").agg(F.sum("count").alias("size"))
    n = n.join(F.broadcast(size), "c").select("h", F.log(F.col("count") / F.col("size")).alias("p"))
    return w.select("row", F.xxhash64("w").alias("h")).join(n, "h").groupBy("row").agg(F.sum("p").alias("share"))


def score_corpus(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """Vocabulary, training and scoring over all documents."""
    # lower-cased once, so that counts and classes see the same words
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("text"))
    counts = word_counts(docs)
    top = vocabulary(docs, counts=counts)
    params = train(docs, top, rounds)
    rows = docs.select("doc_id", F.xxhash64("doc_id", "text").alias("row"), "text")
    out = written(_class_scores(rows, top, Net().params if params is None else params), "class-scores")
    # equal rows add up in the shares, and each has its part
    copies = out.groupBy("row").agg(F.count("*").alias("copies"))
    part = copies.join(shares(rows, top, counts), "row").select("row", (F.col("share") / F.col("copies")).alias("share"))
    out = out.join(part, "row", "left")
    return out.select("doc_id", "n_words", (F.col("log_likelihood") + F.coalesce("share", F.lit(0.0))).alias("log_likelihood"))


def op10_masked_lm_score(spark, sf_dir: str) -> DataFrame:
    """Pseudo-log-likelihood of all documents, in all and for each word."""
    out = score_corpus(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", F.round("log_likelihood", 4).alias("log_likelihood"), F.when(F.col("n_words") > 0, F.round(F.col("log_likelihood") / F.col("n_words"), 6)).alias("per_word"))
