"""Vertex blocks, the ring schedule, requests and messages of an exchange."""

from __future__ import annotations

import gc
import math
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.templates import SplitPlan
from ..sources.graphs import EdgeGraph

_LOCAL: dict[str, str] = {}


def work_folder(spark: SparkSession) -> str:
    """The shared folder that the session names; a folder of this machine where it names none and runs on this machine alone."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = "file://" + tempfile.mkdtemp(prefix="treecount-")
    return _LOCAL[app]


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that no other call gets."""
    return f"{work_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: cuts lineage and survives lost executors."""
    path = fresh_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._store_path = path
    return out


def stored(graph: EdgeGraph) -> EdgeGraph:
    """The graph with its edges in a table, so that what reads them several times does not work them out anew."""
    if getattr(graph.edges, "_store_path", None):
        return graph
    return EdgeGraph(written(graph.edges, "edges"), graph.vertices)


def forget(df: DataFrame) -> None:
    """Delete a table made by `written` that nothing reads any more."""
    path = getattr(df, "_store_path", None)
    if path:
        p = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(p, True)


def release(spark: SparkSession) -> None:
    """Shuffle files of finished jobs go when the driver's JVM collects garbage: let it do so now."""
    gc.collect()
    spark._jvm.System.gc()


def narrowed(df: DataFrame, column: str) -> DataFrame:
    """A column of whole decimals as long if all of them fit, else as they are; works out ``df``."""
    wide = F.col(column) > F.lit((1 << 63) - 1).cast("decimal(38,0)")
    return df if not df.where(wide).isEmpty() else df.withColumn(column, F.col(column).cast("long"))


def block_of(v: Column, blocks: int, scheme: str = "poly") -> Column:
    """Block of a vertex: a hash, never the key itself, which goes with the degree."""
    if scheme == "xxhash":
        return F.pmod(F.xxhash64(v), F.lit(blocks)).cast("int")
    return ((v % F.lit(2147483647) * F.lit(48271) + F.lit(11)) % F.lit(2147483647) % F.lit(blocks)).cast("int")


def ring_offset(receiver: Column, sender: Column, blocks: int) -> Column:
    return F.pmod(block_of(receiver, blocks) - block_of(sender, blocks), F.lit(blocks))


def n_steps(blocks: int, group: int = 3) -> int:
    return math.ceil((blocks - 1) / max(1, (group - 1) // 2))


def ring_schedule(spark: SparkSession, blocks: int, group: int = 3) -> DataFrame:
    """(step, receiver, sender): every ordered pair of blocks once."""
    per = max(1, (group - 1) // 2)
    offset = F.explode(F.sequence(F.lit(1), F.lit(max(1, blocks - 1)))).alias("off")
    s = spark.range(blocks).select(F.col("id").cast("int").alias("receiver"), offset).where(F.col("off") < blocks)
    return s.select((F.floor((F.col("off") - 1) / per) + 1).cast("int").alias("step"), "receiver", F.pmod(F.col("receiver") - F.col("off"), F.lit(blocks)).cast("int").alias("sender"))


def check_schedule(schedule: DataFrame, blocks: int) -> DataFrame:
    """(pairs, repeated, missing) of a schedule; a sound one has P(P-1), 0, 0."""
    n = schedule.groupBy("receiver", "sender").agg(F.count("*").alias("n"))
    return n.agg(F.count("*").cast("long").alias("pairs"), F.sum(F.when(F.col("n") > 1, 1).otherwise(0)).cast("long").alias("repeated")).withColumn("missing", F.lit(blocks * (blocks - 1)).cast("long") - F.col("pairs"))


def build_requests(edges: DataFrame, blocks: int) -> DataFrame:
    """(u, to_blk): which block needs the counts of which vertex of another block."""
    x = edges.select(F.col("dst").alias("u"), block_of(F.col("src"), blocks).alias("to_blk"), block_of(F.col("dst"), blocks).alias("own"))
    return x.where("to_blk <> own").select("u", "to_blk").distinct()


def messages(counts: DataFrame, requests: DataFrame) -> DataFrame:
    """The counts that each block has asked for; zero counts are never sent."""
    return counts.where("cnt > 0").join(requests.withColumnRenamed("u", "v"), "v").select("to_blk", "it", "v", "mask", "cnt")


def pack_tag(sender: Column, receiver: Column, offset: Column, bits: tuple[int, int, int] = (10, 10, 12)) -> Column:
    """One 32-bit integer of sender, receiver and queue offset; a number that does not fit its bits raises an error."""
    a, b, c = bits
    fits = (sender >= 0) & (sender < 1 << a) & (receiver >= 0) & (receiver < 1 << b) & (offset >= 0) & (offset < 1 << c)
    tag = F.shiftleft(sender.cast("int"), b + c).bitwiseOR(F.shiftleft(receiver.cast("int"), c)).bitwiseOR(offset.cast("int"))
    return F.when(fits, tag).otherwise(F.raise_error(F.lit("a part of the tag is too large")).cast("int"))


def unpack_tag(tag: Column, bits: tuple[int, int, int] = (10, 10, 12)) -> tuple[Column, Column, Column]:
    a, b, c = bits
    low = lambda x, n: x.bitwiseAND(F.lit((1 << n) - 1))
    return low(F.shiftrightunsigned(tag, b + c), a), low(F.shiftrightunsigned(tag, c), b), low(tag, c)


def remote_neighbors(edges: DataFrame, blocks: int) -> DataFrame:
    """(blk, step, n): neighbours that a block gets in each ring step."""
    x = edges.select(block_of(F.col("src"), blocks).alias("blk"), ring_offset(F.col("src"), F.col("dst"), blocks).cast("int").alias("step"))
    return x.where("step > 0").groupBy("blk", "step").agg(F.count("*").alias("n"))


def exchange_volume(edges: DataFrame, blocks: int, plan: SplitPlan) -> DataFrame:
    """(step, cut_size, vertices, entries, bytes): what a plan's steps send, by distinct requests."""
    k = plan.template.k
    spark = edges.sparkSession
    rows = [(i + 1, s.sizes[2], math.comb(k, s.sizes[2])) for i, s in enumerate(plan.steps)]
    table = F.broadcast(spark.createDataFrame(rows, "step int, cut_size int, width long"))
    n = build_requests(edges, blocks).agg(F.count("*").alias("vertices"))
    return n.join(table, F.lit(True)).select("step", "cut_size", "vertices", (F.col("vertices") * F.col("width")).alias("entries"), (F.col("vertices") * F.col("width") * 8).alias("bytes"))
