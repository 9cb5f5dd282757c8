"""The cost model of a staged exchange and measures of runs.

``E`` counts directed neighbour pairs, ``P`` blocks; times are in the units of the given rates.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.templates import TreeTemplate, split_plan


def model_steps(spark: SparkSession, template: TreeTemplate, vertices: int, pairs: int, blocks: int, add: float = 1e-9, alpha: float = 1e-4, beta: float = 1e-9) -> DataFrame:
    """(sub, size, step, comp, comm, mem) of every sub-template and ring step: work, transfer time, peak bytes."""
    k = template.k
    rows = [(i + 1, *s.sizes, math.comb(k, s.sizes[0]), math.comb(s.sizes[0], s.sizes[1])) for i, s in enumerate(split_plan(template).steps)]
    plan = F.broadcast(spark.createDataFrame(rows, "sub int, size int, keep int, cut int, sets long, splits long"))
    w = spark.range(1, blocks).select(F.col("id").cast("int").alias("step"))
    per = pairs / blocks**2
    return w.join(plan, F.lit(True)).select(
        "sub", "size", "step",
        (F.col("sets") * F.col("splits") * F.lit(per * add)).alias("comp"),
        (F.lit(alpha) + F.col("sets") * F.lit(8 * per * beta)).alias("comm"),
        (F.col("sets") * F.lit(8.0 * (vertices / blocks + per))).alias("mem"),
    )


def with_overlap(steps: DataFrame) -> DataFrame:
    """Adds ``rho``: the share of a step's transfer hidden by the computing of the step before; none at a cold start."""
    w = Window.partitionBy("sub").orderBy("step")
    before = F.lag("comp").over(w)
    return steps.withColumn("rho", F.when(before.isNotNull(), F.least(before, F.col("comm")) / F.col("comm")))


def totals(steps: DataFrame) -> DataFrame:
    """(sub, comp, comm, mem): total work, transfer not hidden, and peak over the steps."""
    s = with_overlap(steps)
    return s.groupBy("sub", "size").agg(F.sum("comp").alias("comp"), F.sum((1 - F.coalesce("rho", F.lit(0.0))) * F.col("comm")).alias("comm"), F.max("mem").alias("mem"))


def measured_comp(remote: DataFrame, template: TreeTemplate) -> DataFrame:
    """(sub, blk, step, comp): multiply-adds of each block in each step from its counted remote neighbours (blk, step, n)."""
    return _per_step(remote, template).select("sub", "blk", "step", (F.col("n") * F.col("sets") * F.col("splits")).alias("comp"))


def measured_memory(remote: DataFrame, own: DataFrame, template: TreeTemplate) -> DataFrame:
    """(sub, blk, mem): the largest number of counts a block holds in a step: its own vertices' and those of one step's neighbours; own: (blk, v)."""
    x = _per_step(remote, template).join(own, "blk")
    return x.groupBy("sub", "blk").agg(F.max(F.col("sets") * (F.col("v") + F.col("n"))).alias("mem"))


def measured_comm(remote: DataFrame, template: TreeTemplate, alpha: float = 1e-4, beta: float = 1e-9) -> DataFrame:
    """(sub, blk, step, comp, comm): times of a step before waiting, from counted neighbours; 8 bytes a count."""
    x = _per_step(remote, template)
    return x.select("sub", "blk", "step", (F.col("n") * F.col("sets") * F.col("splits") * F.lit(beta)).alias("comp"), (F.lit(alpha) + F.col("n") * F.col("sets") * F.lit(8 * beta)).alias("comm"))


def _per_step(remote: DataFrame, template: TreeTemplate) -> DataFrame:
    rows = [(i + 1, math.comb(template.k, s.sizes[0]), math.comb(s.sizes[0], s.sizes[1])) for i, s in enumerate(split_plan(template).steps)]
    return remote.join(F.broadcast(remote.sparkSession.createDataFrame(rows, "sub int, sets long, splits long")), F.lit(True))


def with_waits(steps: DataFrame) -> DataFrame:
    """Adds ``time`` and ``wait`` to (sub, blk, step, comp, comm).

    A step takes the longer of its transfer and of the computing of the step before; a block waits in a
    step as long as the slowest other block was behind it in the step before.
    """
    before = F.lag("comp").over(Window.partitionBy("sub", "blk").orderBy("step"))
    x = steps.withColumn("time", F.greatest("comm", F.coalesce(before, F.lit(0.0))))
    others = F.max("time").over(Window.partitionBy("sub", "step"))
    late = F.greatest(others - F.col("time"), F.lit(0.0))  # the slowest block itself waits for none
    return x.withColumn("late", late).withColumn("wait", F.coalesce(F.lag("late").over(Window.partitionBy("sub", "blk").orderBy("step")), F.lit(0.0))).drop("late")


def totals_with_waits(steps: DataFrame) -> DataFrame:
    """(sub, blk, comp, comm): total work and transfer of each block, waiting in the transfer, less what computing hides."""
    w = Window.partitionBy("sub", "blk").orderBy("step")
    x = with_waits(steps).withColumn("full", F.col("comm") + F.col("wait"))
    before = F.lag("comp").over(w)
    rho = F.when(before.isNotNull(), F.least(before, F.col("full")) / F.col("full")).otherwise(F.lit(0.0))
    return x.withColumn("rho", rho).groupBy("sub", "blk").agg(F.sum("comp").alias("comp"), F.sum((1 - F.col("rho")) * F.col("full")).alias("comm"))


def fitted_rates(sent: DataFrame) -> DataFrame:
    """(alpha, beta) of transfer times by least squares over (bytes, sec)."""
    return sent.agg(F.regr_intercept("sec", "bytes").alias("alpha"), F.regr_slope("sec", "bytes").alias("beta"))


def waits(times: DataFrame) -> DataFrame:
    """(blk, step, wait) from (blk, step, time): how far the slowest block was ahead in time in the step before."""
    late = F.greatest(F.max("time").over(Window.partitionBy("step")) - F.col("time"), F.lit(0.0))
    x = times.withColumn("late", late)
    return x.select("blk", "step", F.coalesce(F.lag("late").over(Window.partitionBy("blk").orderBy("step")), F.lit(0.0)).alias("wait"))


def large_template_comm(spark: SparkSession, template: TreeTemplate, pairs: int, blocks: list[int], alpha: float = 1e-4, beta: float = 1e-9, wait: float = 0.0) -> DataFrame:
    """(p, comm, comm_printed): transfer time of the first step only, the bound where all others are hidden.

    ``comm_printed`` has the further factor 1 / p that the published bound shows before its volume.
    """
    top = math.comb(template.k, split_plan(template).steps[-1].sizes[2])
    volume = lambda p: 8 * beta * top * pairs / p**2
    return spark.createDataFrame([(p, alpha + wait + volume(p), alpha + wait + volume(p) / p) for p in blocks], "p int, comm double, comm_printed double")


def task_balance(tasks: DataFrame) -> DataFrame:
    """(tasks, max_n, avg_n, sd_n) of neighbours in a task."""
    n = tasks.groupBy("src", "slot").agg(F.count("*").alias("n"))
    return n.agg(F.count("*").alias("tasks"), F.max("n").alias("max_n"), F.round(F.avg("n"), 6).alias("avg_n"), F.round(F.stddev_pop("n"), 6).alias("sd_n"))


def run_log(spark: SparkSession, path: str) -> DataFrame:
    """(stage, task, start_ms, finish_ms, fetch_wait_ms, write_ms, shuffle_read, shuffle_write, peak_mem) of an event log."""
    schema = "Event string, `Stage ID` int, `Task Info` struct<`Task ID`:bigint,`Launch Time`:bigint,`Finish Time`:bigint>, `Task Metrics` struct<`Peak Execution Memory`:bigint,`Shuffle Read Metrics`:struct<`Fetch Wait Time`:bigint,`Remote Bytes Read`:bigint,`Local Bytes Read`:bigint>,`Shuffle Write Metrics`:struct<`Shuffle Bytes Written`:bigint,`Shuffle Write Time`:bigint>>"
    e = spark.read.schema(schema).json(path).where("Event = 'SparkListenerTaskEnd'")
    m = F.col("Task Metrics")
    return e.select(
        F.col("Stage ID").alias("stage"), F.col("Task Info")["Task ID"].alias("task"), F.col("Task Info")["Launch Time"].alias("start_ms"), F.col("Task Info")["Finish Time"].alias("finish_ms"),
        m["Shuffle Read Metrics"]["Fetch Wait Time"].alias("fetch_wait_ms"), (m["Shuffle Write Metrics"]["Shuffle Write Time"] / 1e6).alias("write_ms"),
        (m["Shuffle Read Metrics"]["Remote Bytes Read"] + m["Shuffle Read Metrics"]["Local Bytes Read"]).alias("shuffle_read"), m["Shuffle Write Metrics"]["Shuffle Bytes Written"].alias("shuffle_write"), m["Peak Execution Memory"].alias("peak_mem"),
    )


def time_shares(log: DataFrame) -> DataFrame:
    """(comm_ms, comp_ms, comm_share): waiting for and writing shuffles against the rest."""
    comm = F.sum(F.col("fetch_wait_ms") + F.col("write_ms"))
    total = F.sum(F.col("finish_ms") - F.col("start_ms"))
    return log.agg(comm.alias("comm_ms"), (total - comm).alias("comp_ms"), (comm / total).alias("comm_share"))


def peak_memory(log: DataFrame) -> DataFrame:
    """(stage, peak_mem, moved): the largest execution memory of a task and the bytes shuffled, by stage."""
    return log.groupBy("stage").agg(F.max("peak_mem").alias("peak_mem"), F.sum("shuffle_write").alias("moved"))


def average_concurrency(log: DataFrame) -> DataFrame:
    """(average): tasks running at once, over the time in which any ran."""
    h = concurrency_histogram(log).where("running > 0")
    return h.agg((F.sum(F.col("running") * F.col("ms")) / F.sum("ms")).alias("average"))


def measured_rho(spans: DataFrame) -> DataFrame:
    """(step, rho): the share of each step's transfer during which the step before computed; spans: (step, kind, start, finish)."""
    t, c = (spans.where(F.col("kind") == k).select("step", F.col("start").alias(k[0] + "0"), F.col("finish").alias(k[0] + "1")) for k in ("transfer", "compute"))
    x = t.join(c.withColumn("step", F.col("step") + 1), "step")
    both = F.greatest(F.least("t1", "c1") - F.greatest("t0", "c0"), F.lit(0.0))
    return x.select("step", F.when(F.col("t1") > F.col("t0"), both / (F.col("t1") - F.col("t0"))).otherwise(F.lit(0.0)).alias("rho"))


def speedups(runs: DataFrame, by: str = "mode") -> DataFrame:
    """Adds ``speedup`` over the run of fewest workers ``p`` in each group."""
    first = F.first_value("seconds").over(Window.partitionBy(by).orderBy("p").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return runs.withColumn("speedup", first / F.col("seconds"))


def concurrency_histogram(log: DataFrame) -> DataFrame:
    """(running, ms): how long how many tasks ran at once, by a sweep over starts and ends."""
    ends = log.select(F.col("start_ms").alias("t"), F.lit(1).alias("d")).union(log.select(F.col("finish_ms").alias("t"), F.lit(-1).alias("d")))
    at = ends.groupBy("t").agg(F.sum("d").alias("d"))
    w = Window.orderBy("t")
    x = at.select(F.sum("d").over(w).alias("running"), (F.lead("t").over(w) - F.col("t")).alias("ms")).where("ms is not null")
    return x.groupBy("running").agg(F.sum("ms").alias("ms"))
