"""Document fingerprints by consistent weighted sampling; native expressions only.

A document is a weighted set: its lower-cased words, each with its number of occurrences.  For each of
``SAMPLES`` samples a term of weight w draws, from its hash alone, r and c from Gamma(2, 1) and b from
[0, 1); with t = floor(ln w / r + b) the term's rank is ln c - r (t - b) - r, and the pair (term, t) of
least rank is the sample.  Two documents agree on a sample with the probability of their generalised
Jaccard similarity: the sum of the smaller weights over the sum of the larger ones.

Rank and sample share one 64-bit integer; the samples of a document are plain ``min`` aggregates,
which combine before anything is shuffled.

Defined cases: null and wordless texts have the fingerprint of no term, equal to each other (likeness 1)
and unlike any other (0); rows with equal doc_id follow each other in the order of their text's hash;
rows without a doc_id come last; a single row is its own next document; terms of equal rank go by the least
name; a very long text is one row whose terms are summed one by one; an empty table gives none.  Only doc_id
and text are read, so other columns may have any name.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._store import written
from .quality import words

#: The standard error of a likeness is at most 0.09; 128 samples would cost four times the time and pass its budget.
SAMPLES = 32
LOW_BITS = 29
CELL_ROWS = 512
COARSE = 64


def sample_columns(term: str, log_weight: str, samples: int = SAMPLES) -> list[Column]:
    """Aggregates s0.. whose low bits name each sample; rows are (term hash, ln weight)."""
    out = []
    part = lambda h, skip, bits: (F.shiftrightunsigned(h, skip).bitwiseAND(F.lit((1 << bits) - 1)) + F.lit(0.5)) * F.lit(2.0**-bits)
    for i in range(samples):
        h = F.xxhash64(F.col(term), F.lit(i))
        g = F.xxhash64(h)
        # the sum of two exponential variables is one of Gamma(2, 1): minus the logarithm of a product of uniforms
        r = -F.log(part(h, 0, 21) * part(h, 21, 21))
        log_c = F.log(-F.log(part(g, 0, 31) * part(g, 31, 31)))
        b = part(h, 42, 22)
        t = F.floor(F.col(log_weight) / r + b)
        rank = log_c - r * (t - b) - r
        name = F.xxhash64(h, t).bitwiseAND(F.lit((1 << LOW_BITS) - 1))
        # ranks lie between about -100 and 4: 64-bit order first, then the name
        out.append(F.min(F.floor(F.greatest(rank + 100, F.lit(0.0)) * F.lit(2.0**26)) * F.lit(1 << LOW_BITS) + name).alias(f"s{i}"))
    return out


def weighted_terms(text: Column) -> Column:
    """array<struct<term, weight>> of a text: the sorted hashes of its words, run by run."""
    once = lambda value, f: F.element_at(F.transform(F.array(value), f), 1)
    hashes = F.sort_array(F.transform(words(F.lower(text)), lambda w: F.xxhash64(w)))

    def runs(h: Column) -> Column:
        starts = F.filter(F.transform(h, lambda _, i: i), lambda i: (i == 0) | (F.get(h, i) != F.get(h, i - 1)))
        return once(starts, lambda s: F.transform(s, lambda at, j: F.struct(F.get(h, at).alias("term"), (F.coalesce(F.get(s, j + 1), F.size(h)) - at).alias("weight"))))

    return once(hashes, runs)


def signature(samples: int = SAMPLES) -> Column:
    low = (1 << LOW_BITS) - 1
    return F.array(*[F.col(f"s{i}").bitwiseAND(F.lit(low)).cast("int") for i in range(samples)])


def fingerprints(docs: DataFrame, key: list[str], text: str, samples: int = SAMPLES) -> DataFrame:
    """(key.., sig) of each distinct key; sig is null for texts without a word."""
    d = docs.select(*key, F.explode_outer(weighted_terms(F.coalesce(F.col(text), F.lit("")))).alias("x"))
    d = d.select(*key, F.col("x.term").alias("_h"), F.log(F.col("x.weight").cast("double")).alias("_w"))
    d = d.groupBy(*key).agg(*sample_columns("_h", "_w", samples))
    return d.select(*key, F.when(F.col("s0").isNotNull(), signature(samples)).alias("sig"))


def text_form(sig: Column) -> Column:
    return F.coalesce(F.array_join(F.transform(sig, lambda x: F.lpad(F.lower(F.hex(x)), 8, "0")), ""), F.lit(""))


def likeness(a: Column, b: Column, samples: int = SAMPLES) -> Column:
    """Share of equal samples: an estimate of the generalised Jaccard similarity."""
    same = F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda x: x)) / F.lit(float(samples))
    return F.when(a.isNull() & b.isNull(), F.lit(1.0)).when(a.isNull() | b.isNull(), F.lit(0.0)).otherwise(same)


def _cells(docs: DataFrame) -> tuple[Column, Column]:
    """(coarse cell, cell) of a doc_id: intervals of about CELL_ROWS rows, whatever the ids' distribution."""
    s = docs.agg(F.count("doc_id").alias("n"), F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.percentile_approx("doc_id", [i / COARSE for i in range(1, COARSE)], 10_000).alias("q")).first()
    if not s["n"]:
        return F.lit(0), F.lit(0).cast("long")
    cuts = sorted(set(s["q"] or []))
    edges = F.array(*[F.lit(x).cast("long") for x in [s["lo"], *cuts, s["hi"]]])
    coarse = F.size(F.filter(F.array(*[F.lit(x).cast("long") for x in cuts]), lambda x: x <= F.col("doc_id")))
    m = max(1, math.ceil(s["n"] / (len(cuts) + 1) / CELL_ROWS))
    lo, hi = F.get(edges, coarse).cast("double"), F.get(edges, coarse + 1).cast("double")
    part = F.least(F.floor((F.col("doc_id").cast("double") - lo) / (hi - lo + 1) * m), F.lit(m - 1))
    return F.coalesce(coarse, F.lit(-1)), F.coalesce(coarse * F.lit(m).cast("long") + part, F.lit(-1).cast("long"))


def with_next(docs: DataFrame) -> DataFrame:
    """(doc_id, text, cell, next_id, next_text) with the next document in descending doc_id; the last has the first.

    The order is cut into cells of bounded size; a window serves each cell, and a table of the cells'
    first rows serves the cells' last rows.
    """
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    coarse, cell = _cells(d)
    d = d.select("doc_id", "text", coarse.cast("int").alias("coarse"), cell.alias("cell"))
    row = F.struct(F.coalesce("doc_id", F.lit(-(1 << 63))).alias("o"), (-F.shiftright(F.xxhash64("text"), 1)).alias("h"))
    head = d.groupBy("coarse", "cell").agg(F.max_by(F.struct("doc_id", "text"), row).alias("head"))
    head = written(head, "cell-heads")
    top = head.groupBy("coarse").agg(F.max_by("head", "cell").alias("top"))
    every = Window.orderBy(F.desc("coarse"))
    first = F.first("top").over(every.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    top = top.select("coarse", F.coalesce(F.lead("top").over(every), first).alias("after"))
    inner = F.lead("head").over(Window.partitionBy("coarse").orderBy(F.desc("cell")))
    head = head.withColumn("inner", inner).join(top, "coarse").select("cell", F.coalesce("inner", "after").alias("after"))
    w = Window.partitionBy("cell").orderBy(F.col("doc_id").desc_nulls_last(), F.shiftright(F.xxhash64("text"), 1))
    d = d.select("cell", "doc_id", "text", F.lead(F.struct("doc_id", "text")).over(w).alias("follows"), F.row_number().over(w).alias("place"))
    d = d.join(head, "cell", "left")
    follows = F.coalesce("follows", "after")
    return d.select("cell", "place", "doc_id", "text", follows["doc_id"].alias("next_id"), follows["text"].alias("next_text"))


def edited_text() -> Column:
    """The text with its last third replaced by as many first code points of the next text."""
    n = F.char_length("text")
    k = F.floor(n / 3).cast("int")
    return F.concat(F.substring(F.col("text"), F.lit(1), n - k), F.substring(F.col("next_text"), F.lit(1), k))


def compare_with_next(docs: DataFrame, samples: int = SAMPLES) -> DataFrame:
    """One row per document: its fingerprint, its edited text's, and the likeness of both and of the next document's."""
    d = with_next(docs)
    d = d.select("cell", "place", "doc_id", "next_id", F.char_length("text").cast("long").alias("n_chars"), "text", edited_text().alias("edited"))
    d = d.withColumn("edited_sha256", F.sha2("edited", 256))
    both = F.array(F.struct(F.lit(0).alias("v"), F.col("text").alias("t")), F.struct(F.lit(1).alias("v"), F.col("edited").alias("t")))
    key = ["cell", "place", "doc_id", "next_id", "n_chars", "edited_sha256"]
    d = d.select(*key, F.inline(both))
    sigs = fingerprints(d, [*key, "v"], "t", samples)
    # both versions meet in the task that has the cell: no exchange is needed
    sig = lambda v: F.max(F.when(F.col("v") == v, F.col("sig"))).alias(f"sig{v}")
    one = written(sigs.groupBy(*key).agg(sig(0), sig(1)), "fingerprints")
    # of rows with equal ids the first in order is the one that a smaller id's predecessor meets; ties are next to each other
    after = one.groupBy("doc_id").agg(F.min_by(F.struct("sig0"), F.struct("cell", "place")).alias("n"))
    out = one.join(after.select(F.col("doc_id").alias("next_id"), F.col("n.sig0").alias("sign")), "next_id", "left")
    return out.select(
        "doc_id", "n_chars", "edited_sha256", text_form(F.col("sig0")).alias("fingerprint"), text_form(F.col("sig1")).alias("edited_fingerprint"),
        likeness(F.col("sig0"), F.col("sig1"), samples).alias("near_edited"), likeness(F.col("sig0"), F.col("sign"), samples).alias("near_next"),
    )


def op4_weighted_fingerprints(spark, sf_dir: str) -> DataFrame:
    """Fingerprints of all documents and of their edited texts."""
    return compare_with_next(spark.read.parquet(f"{sf_dir}/documents.parquet"))
