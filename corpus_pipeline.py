"""From raw documents to packed sequences: quality, lines, near copies, personal data, packing.

All stages but the last return the columns of documents and leave any other column as it is, whatever its
name.  Nulls, repeated rows, empty tables and long texts are handled as the stages' operators say; rows
that share a doc_id are one document to the near-copy stage and stay or go together.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treecount.llm import linededup, neardup, packing, privacy, quality
from treecount.llm._store import forget, release, scratch, written


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the standard policy keeps."""
    columns = docs.columns
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("own"), "text")
    book = quality.ledger(own, ("own",))
    # a generator keeps the optimizer from moving the filter, and with it a copy of every measurement, below them
    book = book.select(F.inline(F.array(F.struct("own", "fail_bits"))))
    return book.where(quality.verdict(quality.POLICIES[1])).select(*[F.col("own").getField(c).alias(c) for c in columns])


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with the first line of each class of near copies."""
    release(spark)  # the stage before is written: its shuffle files may go
    columns = docs.columns
    own = F.struct(*[F.col(f"`{c}`") for c in columns]).alias("own")
    out = linededup.dedup_lines(docs.select("doc_id", "text", own))
    new = {"text": F.col("text"), "n_chars": F.char_length("text").cast("long")}
    return out.select(*[new.get(c, F.col("own").getField(c)).alias(c) for c in columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The least document of each near-duplicate component."""
    release(spark)
    kept = neardup.near_duplicates(docs).where("kept").select(F.col("doc_id").alias("_id")).distinct()
    return docs.join(kept, docs["doc_id"].eqNullSafe(kept["_id"]), "left_semi")


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data and the terms that reveal them replaced."""
    release(spark)
    out = privacy.sanitise(docs)
    return out.select(*[(F.char_length("text").cast("long") if c == "n_chars" else F.col(f"`{c}`")).alias(c) for c in docs.columns])


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in windows of 2048 ids."""
    release(spark)
    return packing.pack(docs).select("sequence_id", "offset", "doc_id", "start", "length", "doc_tokens", "ids")


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("near_dedup", near_dedup),
    ("personal_data", personal_data),
    ("pack", pack),
]

#: Tokenisation and fuzzy components are beyond SQL; tests/llm/test_cases.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn over the documents, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        before = docs
        with scratch(spark) as keep:
            docs = keep(written(stage(spark, docs, sf_dir), f"stage-{name}"))
        forget(before)
    return STAGES[-1][1](spark, docs, sf_dir)
