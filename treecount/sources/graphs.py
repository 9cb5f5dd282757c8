"""Graphs over the given tables, from files, and from a generator.

A graph is a table of pairs made clean by `edges_of`: both directions, no loops, no repeats, no nulls.
A vertex id is ``key * 16 + kind``, so that entities of different tables never share an id.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

KIND = {"customer": 0, "order": 1, "part": 2, "supplier": 3, "nation": 4, "segment": 5, "priority": 6, "status": 7, "vector": 8, "user": 9, "page": 10, "link": 11, "document": 12, "line": 13, "conversation": 14, "event_type": 15}
EDGE_SCHEMA = "src long, dst long"


@dataclass
class EdgeGraph:
    """Directed edges in both directions; vertices default to the ends of edges."""

    edges: DataFrame
    vertices: DataFrame | None = None

    def nodes(self) -> DataFrame:
        return self.vertices if self.vertices is not None else self.edges.select(F.col("src").alias("v")).distinct()


def vid(key: Column, kind: str) -> Column:
    return (key.cast("long") * 16 + KIND[kind]).alias("v")


def pairs(df: DataFrame, a: Column, b: Column) -> DataFrame:
    return df.select(a.alias("a"), b.alias("b"))


def edges_of(raw: DataFrame) -> DataFrame:
    """Both directions of the distinct pairs of two columns; loops and nulls are dropped."""
    a, b = (F.col(c).cast("long") for c in raw.columns[:2])
    once = raw.select(a.alias("a"), b.alias("b")).where("a is not null and b is not null and a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    # one pass over the distinct pairs gives both directions
    both = F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))))
    return once.select(both.alias("e")).select("e.src", "e.dst")


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _code(df: DataFrame, column: str) -> DataFrame:
    """(value, code): dense numbers of the distinct values in binary order; for columns of few values."""
    return df.select(F.col(column).alias("value")).distinct().withColumn("code", F.dense_rank().over(Window.orderBy("value")).cast("long"))


def part_supplier(spark: SparkSession, d: str, since: str | None = None, until: str | None = None) -> DataFrame:
    li = _t(spark, d, "lineitem")
    if since:
        li = li.where(F.col("l_shipdate") >= F.lit(since).cast("timestamp_ntz"))
    if until:
        li = li.where(F.col("l_shipdate") < F.lit(until).cast("timestamp_ntz"))
    return pairs(li, vid(F.col("l_partkey"), "part"), vid(F.col("l_suppkey"), "supplier"))


def cust_part(spark: SparkSession, d: str) -> DataFrame:
    o, li = _t(spark, d, "orders").select("o_orderkey", "o_custkey"), _t(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    return pairs(li.join(o, li["l_orderkey"] == o["o_orderkey"]), vid(F.col("o_custkey"), "customer"), vid(F.col("l_partkey"), "part"))


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return pairs(_t(spark, d, "lineitem"), vid(F.col("l_orderkey"), "order"), vid(F.col("l_partkey"), "part"))


def co_order(spark: SparkSession, d: str) -> DataFrame:
    # an order's parts as one list: its pairs come out of it without a join
    li = _t(spark, d, "lineitem").where("l_orderkey is not null").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("s"))
    x = li.select(F.explode("s").alias("p"), "s").select("p", F.explode(F.expr("filter(s, q -> q > p)")).alias("q"))
    return pairs(x, vid(F.col("p"), "part"), vid(F.col("q"), "part"))


def hub(spark: SparkSession, d: str) -> DataFrame:
    o, c = _t(spark, d, "orders"), _t(spark, d, "customer")
    order, cust = vid(F.col("o_orderkey"), "order"), vid(F.col("c_custkey"), "customer")
    out = pairs(o, order, vid(F.col("o_custkey"), "customer"))
    for column, kind in (("o_orderpriority", "priority"), ("o_orderstatus", "status")):
        # a handful of values: the code table has a fixed size
        out = out.unionByName(pairs(o.join(F.broadcast(_code(o, column)), F.col(column) == F.col("value")), order, vid(F.col("code"), kind)))
    out = out.unionByName(pairs(c, cust, vid(F.col("c_nationkey"), "nation")))
    return out.unionByName(pairs(c.join(F.broadcast(_code(c, "c_mktsegment")), F.col("c_mktsegment") == F.col("value")), cust, vid(F.col("code"), "segment")))


def user_next(spark: SparkSession, d: str) -> DataFrame:
    """Consecutive users of the event stream; a window serves each day, and the days' ends are joined up."""
    e = _t(spark, d, "events").select(F.to_date("ts").alias("day"), "ts", "event_id", "user_id")
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    inner = e.select("user_id", F.lead("user_id").over(w).alias("next"))
    at = F.struct("ts", "event_id")
    ends = e.groupBy("day").agg(F.min_by("user_id", at).alias("first"), F.max_by("user_id", at).alias("last"))
    across = ends.select(F.col("last").alias("user_id"), F.lead("first").over(Window.orderBy("day")).alias("next"))  # a row a day
    return pairs(inner.union(across).where("next is not null"), vid(F.col("user_id"), "user"), vid(F.col("next"), "user"))


def page_link(spark: SparkSession, d: str) -> DataFrame:
    p = _t(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return pairs(p.join(_dense(p, "href"), "href"), vid(F.col("page_id"), "page"), vid(F.col("code"), "link"))


def _dense(df: DataFrame, column: str) -> DataFrame:
    """Dense numbers of many distinct values in binary order: ranks within first bytes plus the counts before."""
    v = df.select(column).distinct().withColumn("_b", F.substring(column, 1, 12))
    size = v.groupBy("_b").agg(F.count("*").alias("_n"))
    before = F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))
    base = size.select("_b", F.coalesce(before, F.lit(0)).alias("_base"))
    rank = F.row_number().over(Window.partitionBy("_b").orderBy(column))
    return v.join(base, "_b").select(column, (F.col("_base") + rank).cast("long").alias("code"))


def knn(spark: SparkSession, d: str, threshold: float = 0.3, block: int = 8192) -> DataFrame:
    """Vectors with a cosine above the threshold, exactly: matrix products of blocks of ``block`` rows, as many as the rows ask for.

    Vectors travel as they are stored, once for each other block; the products are worked out some rows at a time.
    """
    e = _t(spark, d, "embeddings").select("vec_id", F.col("embedding").alias("x")).where("vec_id is not null and x is not null")
    n = -(-e.count() // block) or 1
    e = e.withColumn("i", F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    r = e.select((F.least("i", "j") * n + F.greatest("i", "j")).alias("pq"), "i", "vec_id", "x")
    # a pair of blocks is a task of its own: a cut of the left rows more where the blocks are few
    cuts = max(1, 32 // (n * (n + 1)))
    if cuts > 1:
        r = r.withColumn("cut", F.explode(F.sequence(F.lit(0), F.lit(cuts - 1)))).withColumn("pq", F.col("pq") * cuts + F.col("cut")).drop("cut")
    r = r.repartition(2 * cuts * n * (n + 1), "pq")

    def near(table):
        import numpy as np
        import pyarrow as pa

        ids, part = (table.column(c).to_numpy() for c in ("vec_id", "i"))
        x = np.stack([v.values.to_numpy(zero_copy_only=False) for v in table.column("x")]).astype(np.float64)
        x = x / np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-300)
        pq, cut = divmod(table.column("pq")[0].as_py(), cuts)
        p, q = divmod(pq, n)
        left, right = np.flatnonzero(part == p), np.flatnonzero(part == q)
        left = left[ids[left] % cuts == cut]
        y, out = x[right].T, []
        for lo in range(0, len(left), 512):
            a, b = np.nonzero(x[left[lo : lo + 512]] @ y > threshold)
            a, b = ids[left[lo + a]], ids[right[b]]
            once = a < b if p == q else slice(None)
            out.append((np.minimum(a, b)[once], np.maximum(a, b)[once]))
        a, b = (np.concatenate(c) for c in zip(*out)) if out else (np.empty(0, np.int64), np.empty(0, np.int64))
        return pa.table({"a": a, "b": b})

    out = r.groupBy("pq").applyInArrow(near, "a long, b long")
    return pairs(out, vid(F.col("a"), "vector"), vid(F.col("b"), "vector"))


def doc_line(spark: SparkSession, d: str, min_len: int = 20) -> DataFrame:
    x = _t(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    x = x.where(F.char_length("line") >= min_len)
    return pairs(x, vid(F.col("doc_id"), "document"), (F.shiftright(F.xxhash64("line"), 5) * 16 + KIND["line"]).alias("v"))


def conv_text(spark: SparkSession, d: str) -> DataFrame:
    x = _t(spark, d, "conversations")
    return pairs(x, vid(F.col("conv_id"), "conversation"), (F.shiftright(F.xxhash64("role", "text"), 5) * 16 + KIND["line"]).alias("v"))


def user_prop(spark: SparkSession, d: str) -> DataFrame:
    e = _t(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return pairs(e, vid(F.col("user_id"), "user"), vid(F.col("k"), "line"))


#: Generator quadrant probabilities by skew; our own choice.
SKEW = {1: (25, 25, 25, 25), 3: (45, 22, 22, 11), 8: (57, 19, 19, 5)}


def hash_bits(x: Column, salt: int) -> Column:
    """A number below 2^31 - 1 from a number below it; both SQL engines agree on it."""
    p = 2147483647
    # squares, as sums and products by constants alone would tie the numbers of different salts together
    a = (x * 48271 + F.lit(salt * 7919 % p)) % F.lit(p)
    a = (a * a + F.lit(salt % p)) % F.lit(p)
    a = (a * 16807 + F.lit(12345)) % F.lit(p)
    return a * a % F.lit(p)


def rmat(spark: SparkSession, scale: int, n_edges: int, skew: int = 3, seed: int = 42) -> DataFrame:
    """Recursive-matrix pairs: edge i falls ``scale`` times into a quadrant by hashes of i."""
    a, b, c, _ = SKEW[skew]
    i = spark.range(n_edges).withColumn("i", F.col("id") % F.lit(2147483647))
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        q = hash_bits(F.col("i"), seed * 1000 + level) % 100
        src = src * 2 + (q >= a + b).cast("long")
        dst = dst * 2 + (((q >= a) & (q < a + b)) | (q >= a + b + c)).cast("long")
    return i.select(src.alias("a"), dst.alias("b"))


SOURCES = {"part_supplier": part_supplier, "cust_part": cust_part, "order_part": order_part, "co_order": co_order, "hub": hub, "user_next": user_next, "page_link": page_link, "knn": knn, "doc_line": doc_line, "conv_text": conv_text}


def graph(spark: SparkSession, d: str, name: str) -> EdgeGraph:
    return EdgeGraph(edges_of(SOURCES[name](spark, d)))


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """Edges from csv, json, parquet or text (two numbers a line)."""
    if fmt == "text":
        x = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).select(x[0].cast("long").alias("src"), x[1].cast("long").alias("dst"))
    return spark.read.schema(EDGE_SCHEMA).format(fmt).load(path)


def write_edge_list(edges: DataFrame, path: str, fmt: str = "csv") -> str:
    edges.write.mode("overwrite").format(fmt).save(path)
    return path


def save_bucketed(edges: DataFrame, name: str, buckets: int) -> DataFrame:
    """Edges bucketed by their far end, so that joins with counts of that end need no exchange."""
    edges.write.mode("overwrite").bucketBy(buckets, "dst").sortBy("dst").saveAsTable(name)
    return edges.sparkSession.table(name)
