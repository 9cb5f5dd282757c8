"""Edges and marks from the event stream, as batch tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def events(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/events.parquet")


def seconds(ts: str = "ts"):
    """Whole seconds since 1970, whatever the session's time zone."""
    return F.expr(f"timestampdiff(SECOND, timestamp_ntz'1970-01-01 00:00:00', {ts})")


def user_coactive(spark: SparkSession, d: str, within: int = 60) -> DataFrame:
    """(a, b, n): pairs of users with events at most ``within`` seconds apart, a < b.

    An interval join: events meet in buckets of that length and the next one, never all with all.
    """
    e = events(spark, d).select("event_id", "user_id", seconds().alias("s"))
    x = e.select(F.col("event_id").alias("i"), F.col("user_id").alias("u"), F.col("s").alias("t"), F.explode(F.array(*[F.floor(F.col("s") / within) + k for k in (-1, 0, 1)])).alias("g"))
    y = e.select(F.col("event_id").alias("j"), F.col("user_id").alias("w"), F.col("s").alias("z"), F.floor(F.col("s") / within).alias("g"))
    near = x.join(y, "g").where((F.col("u") < F.col("w")) & (F.abs(F.col("t") - F.col("z")) <= within))
    return near.groupBy(F.col("u").alias("a"), F.col("w").alias("b")).agg(F.count("*").alias("n"))


def asof_prev(spark: SparkSession, d: str, kind: str = "purchase") -> DataFrame:
    """(event_id, prev_id): each event with the user's latest earlier event of a kind; one sort a user, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return events(spark, d).select("event_id", F.last(F.when(F.col("event_type") == kind, F.col("event_id")), ignorenulls=True).over(w).alias("prev_id"))


def next_users(spark: SparkSession, d: str) -> DataFrame:
    """(event_id, user_id, next_user): the user of the event that follows; days are joined up at their ends."""
    e = events(spark, d).select(F.to_date("ts").alias("day"), "ts", "event_id", "user_id")
    at = F.struct("ts", "event_id")
    first = e.groupBy("day").agg(F.min_by("user_id", at).alias("first"))
    after = first.select("day", F.lead("first").over(Window.orderBy("day")).alias("after"))  # a row a day
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    x = e.withColumn("nx", F.lead("user_id").over(w)).join(F.broadcast(after), "day")  # days are few
    last = F.lead("event_id").over(w).isNull()
    return x.select("event_id", "user_id", F.when(last, F.col("after")).otherwise(F.col("nx")).alias("next_user"))


def growth(spark: SparkSession, d: str) -> DataFrame:
    """(event_id, n): events up to and with each one; running counts of a day on top of those of the days before."""
    e = events(spark, d).select(F.to_date("ts").alias("day"), "ts", "event_id")
    per = e.groupBy("day").agg(F.count("*").alias("n"))
    base = per.select("day", F.coalesce(F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # a row a day
    w = Window.partitionBy("day").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("k", F.count("*").over(w)).join(F.broadcast(base), "day").select("event_id", (F.col("base") + F.col("k")).alias("n"))


def recent_activity(spark: SparkSession, d: str, span: int = 3600) -> DataFrame:
    """(event_id, n): the user's events of the last ``span`` seconds, itself included."""
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-span, 0)
    return events(spark, d).select("event_id", "user_id", seconds().alias("s")).select("event_id", F.count("*").over(w).alias("n"))


def edges_by_period(spark: SparkSession, d: str) -> DataFrame:
    """(month, weekday, n) of orders; weekday 1 is Sunday."""
    o = spark.read.parquet(f"{d}/orders.parquet").select("o_orderdate")
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.dayofweek("o_orderdate").alias("weekday")).agg(F.count("*").alias("n"))


def typed_pairs(spark: SparkSession, d: str, since: str, until: str) -> DataFrame:
    """(a, b): users and the kinds of their events in a span of time."""
    e = events(spark, d).where((F.col("ts") >= F.lit(since).cast("timestamp_ntz")) & (F.col("ts") < F.lit(until).cast("timestamp_ntz")))
    return e.select(F.col("user_id").alias("a"), F.col("event_type").alias("b")).distinct()
