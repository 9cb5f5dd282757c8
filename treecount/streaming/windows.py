"""The event stream as a changing graph: degrees in windows, sessions, first edges, late rows, star counts.

Each function runs the stream over what is there now and returns what it has emitted, as a table in the
shared folder.  Windows are emitted once, when the watermark has passed them, so state is bounded by
the open windows (or, for first edges, by the distinct edges).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.exchange import fresh_path, written

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream(spark: SparkSession, path: str, files: int | None = None) -> DataFrame:
    """The events below a path as a stream, ``files`` files a batch; the time column carries a time zone, as watermarks ask."""
    reader = spark.readStream.schema(SCHEMA)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(out: DataFrame, name: str) -> DataFrame:
    """All rows that a stream emits until its source is read up."""
    spark = out.sparkSession
    path = fresh_path(spark, name)
    query = out.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-state").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(out.schema).parquet(path)


def text_of(t):
    return F.date_format(t, "yyyy-MM-dd HH:mm:ss")


def window_degree(events: DataFrame, width: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(start, user_id, deg): events of each user in each window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    n = events.withWatermark("ts", delay).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("deg"))
    return n.select(text_of(F.col("w.start")).alias("start"), "user_id", "deg")


def window_edges(events: DataFrame, width: str, slide: str, delay: str = "1 hour") -> DataFrame:
    """(start, n): events of each sliding window."""
    n = events.withWatermark("ts", delay).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n"))
    return n.select(text_of(F.col("w.start")).alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(user_id, start, n): runs of a user's events without a gap."""
    n = events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return n.select("user_id", text_of(F.col("w.start")).alias("start"), "n")


def dedupe(events: DataFrame) -> DataFrame:
    """(user_id, event_type) at its first occurrence; the state holds the distinct pairs."""
    return events.select("user_id", "event_type").dropDuplicates(["user_id", "event_type"])


def late_demo(spark: SparkSession, events: DataFrame, since: str, delay: str = "1 hour") -> DataFrame:
    """(start, n) by day where the last of three batches brings only rows older than the watermark: they are dropped.

    Rows are judged late by the watermark that held when the batch before began, so two batches come first.
    """
    path = fresh_path(spark, "late-events")
    new = F.col("ts") >= F.lit(since).cast("timestamp_ntz")
    even = F.col("event_id") % 2 == 0
    for part in (events.where(new & even), events.where(new & ~even), events.where(~new)):
        part.coalesce(1).write.mode("append").parquet(path)  # one file a batch, read in the order of their times
    s = stream(spark, path, 1)
    n = s.withWatermark("ts", delay).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(n.select(text_of(F.col("w.start")).alias("start"), "n"), "late")


def star_counts(events: DataFrame, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    """(start, star3, star4): stars of three and four vertices at the users of each window, kept batch by batch."""
    spark = events.sparkSession
    path = fresh_path(spark, "stars")
    d = F.col("deg").cast("decimal(38,0)")

    def keep(batch: DataFrame, number: int) -> None:
        # a window is complete when it is emitted, so its sums are final; a retried batch overwrites its own folder
        stars = batch.groupBy("start").agg(F.sum((d * (d - 1) / 2).cast("long")).alias("star3"), F.sum((d * (d - 1) * (d - 2) / 6).cast("long")).alias("star4"))
        stars.write.mode("overwrite").parquet(f"{path}/batch={number}")

    query = window_degree(events, width, None, delay).writeStream.foreachBatch(keep).option("checkpointLocation", f"{path}-state").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    found = spark.read.schema("start string, star3 long, star4 long, batch int").parquet(path)
    return written(found.groupBy("start").agg(F.sum("star3").alias("star3"), F.sum("star4").alias("star4")), "star-counts")
