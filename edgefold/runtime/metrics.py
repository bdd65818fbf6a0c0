"""Run measures: message and collision counts, speed-up, scaling slope, computing share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def fold_collisions(edges: DataFrame) -> DataFrame:
    """(messages, targets): messages of a step in which all emit, and their distinct targets."""
    return edges.agg(F.count("*").alias("messages"), F.countDistinct("dst").alias("targets"))


def speedup(times: DataFrame) -> DataFrame:
    """(workers, seconds, speedup): against the smallest number of workers."""
    first = F.first("seconds").over(Window.orderBy("workers").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return times.select("workers", "seconds", (first / F.col("seconds")).alias("speedup"))


def scaling_slope(times: DataFrame) -> DataFrame:
    """(slope): of log seconds against log size; 1 is in proportion."""
    return times.agg(F.regr_slope(F.ln("seconds"), F.ln("size")).alias("slope"))


def group_share(spark: SparkSession, group: str) -> tuple[float, float]:
    """(compute_ms, wait_ms) over the stages of a job group, from the session's own status store: no event log needed."""
    context = spark.sparkContext
    tracker, store, stages = context.statusTracker(), context._jsc.sc().statusStore(), set()
    for job in tracker.getJobIdsForGroup(group):
        stages |= set(info.stageIds if (info := tracker.getJobInfo(job)) else ())
    compute = wait = 0.0
    for stage in stages:
        if tracker.getStageInfo(stage) is not None:
            data = store.lastStageAttempt(stage)
            lost = data.shuffleFetchWaitTime() + data.shuffleWriteTime() / 1_000_000
            compute, wait = compute + max(0.0, data.executorRunTime() - lost), wait + lost
    return compute, wait


def compute_share(spark: SparkSession, event_log: str) -> DataFrame:
    """(compute_ms, wait_ms, share) over the tasks of an event log: run time without shuffle waits and writes."""
    metrics = "struct<`Executor Run Time`:long,`Shuffle Read Metrics`:struct<`Fetch Wait Time`:long>,`Shuffle Write Metrics`:struct<`Shuffle Write Time`:long>>"
    tasks = spark.read.schema(f"Event string, `Task Metrics` {metrics}").json(event_log).where("Event = 'SparkListenerTaskEnd'")
    m = F.col("Task Metrics")
    wait = F.coalesce(m["Shuffle Read Metrics"]["Fetch Wait Time"], F.lit(0)) + F.coalesce(m["Shuffle Write Metrics"]["Shuffle Write Time"], F.lit(0)) / 1_000_000
    run = F.coalesce(m["Executor Run Time"], F.lit(0))
    sums = tasks.agg(F.sum(F.greatest(run - wait, F.lit(0))).alias("compute_ms"), F.sum(wait).alias("wait_ms"))
    return sums.select("compute_ms", "wait_ms", (F.col("compute_ms") / (F.col("compute_ms") + F.col("wait_ms"))).alias("share"))
