"""Measures of a synchronisation from its transcript and states."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from replica_sync.protocols.base import Replicas, SyncResult, sizes, without


def summarise(transcript: DataFrame) -> DataFrame:
    """One METRIC row per session: bytes by kind, messages, round trips (a stream of cells counts with the message before it)."""
    grouped = transcript.groupBy("sid", "protocol").agg(
        F.sum("metadata_bytes").alias("metadata_bytes"),
        F.sum("redundant_bytes").alias("redundant_bytes"),
        F.sum(F.col("metadata_bytes") + F.col("payload_bytes")).alias("total_bytes"),
        F.count_if((F.col("kind") != "cells") | (F.col("seq") == 1)).alias("messages"),
    )
    required = F.col("total_bytes") - F.col("metadata_bytes") - F.col("redundant_bytes")
    return grouped.withColumn("required_bytes", required).withColumn("rtt", F.col("messages") / 2)


def required_bytes(r: Replicas) -> DataFrame:
    """Both minimal differences, straight from the sets: what any converging protocol has to ship."""
    both = without(r.a, r.b).unionByName(without(r.b, r.a))
    return both.groupBy("sid").agg(F.sum("nbytes").alias("required_bytes"))


def converged(result: SyncResult) -> DataFrame:
    """sid, apart: parts that one final state has and the other lacks (none once converged)."""
    apart = without(result.state_a, result.state_b).unionByName(without(result.state_b, result.state_a))
    return result.transcript.select("sid").distinct().join(sizes(apart, "apart"), "sid", "left").withColumn("apart", F.coalesce("apart", F.lit(0)))


def reduction(metrics: DataFrame, reference: str) -> DataFrame:
    """metrics with s and protocol: ratio and saving of total bytes against a reference protocol at the same s."""
    base = metrics.where(F.col("protocol") == reference).select("s", F.col("total_bytes").alias("reference_bytes"))
    return metrics.join(base, "s").withColumn("ratio", F.col("reference_bytes") / F.col("total_bytes")).withColumn("saving", 1 - F.col("total_bytes") / F.col("reference_bytes"))


def redundancy_peak(metrics: DataFrame) -> DataFrame:
    """Per protocol and load factor the similarity at which most redundant bytes are sent, and how many."""
    return metrics.groupBy("protocol", "load_factor").agg(F.max_by("s", "redundant_bytes").alias("peak_s"), F.max("redundant_bytes").alias("peak_bytes"))


def crossover(metrics: DataFrame, first: str, second: str) -> DataFrame:
    """The similarities at which the cheaper of two protocols changes."""
    wide = metrics.where(F.col("protocol").isin(first, second)).groupBy("s").pivot("protocol", [first, second]).agg(F.first("total_bytes"))
    better = wide.withColumn("better", F.when(F.col(first) <= F.col(second), first).otherwise(second))
    return better.withColumn("before", F.lag("better").over(Window.orderBy("s"))).where("before is not null and before != better").select("s", "before", F.col("better").alias("after"))


STAGE_COST = "stage int, name string, tasks int, rows_read bigint, shuffle_rows bigint, shuffle_bytes bigint, spilled_bytes bigint, task_seconds double, wall_seconds double"


def engine_cost(spark: SparkSession, work: Callable[[], object]) -> DataFrame:
    """What the engine did for all jobs that work starts: one row a stage that ran, from the session's own status store.

    wall_seconds is the time of the whole call, on each row. The rows are as many as the plan has stages, whatever the data.
    The store keeps the latest spark.ui.retainedStages stages and lets go of skipped ones first, which cost nothing; where it
    has let go of more, this raises rather than count too little.
    """
    sc, tag = spark.sparkContext, f"cost-{uuid.uuid4().hex}"
    sc.addJobTag(tag)
    began = time.monotonic()
    try:
        work()
    finally:
        sc.removeJobTag(tag)
    wall = time.monotonic() - began
    core = sc._jsc.sc()
    core.listenerBus().waitUntilEmpty()
    store, wanted, gone, rows = core.statusStore(), {}, set(), []
    jobs = store.jobsList(None)
    for i in range(jobs.size()):
        job = jobs.apply(i)
        if job.jobTags().contains(tag):
            ids = job.stageIds()
            wanted[job.jobId()] = ({ids.apply(k) for k in range(ids.size())}, job.numSkippedStages())
    for i in sorted(set().union(*(ids for ids, _ in wanted.values()))):
        try:
            s = store.lastStageAttempt(i)
        except Py4JJavaError as e:
            if "NoSuchElementException" not in str(e.java_exception):
                raise
            gone.add(i)
            continue
        if s.numCompleteTasks():  # others were skipped: their exchange was there
            rows.append((i, s.name(), s.numCompleteTasks(), s.inputRecords() + s.shuffleReadRecords(), s.shuffleWriteRecords(), s.shuffleWriteBytes(), s.memoryBytesSpilled() + s.diskBytesSpilled(), s.executorRunTime() / 1000, wall))
    for job, (ids, skipped) in wanted.items():
        if len(ids & gone) > skipped:
            raise RuntimeError(f"stages of job {job} that ran are no longer in the status store: raise spark.ui.retainedStages")
    return spark.createDataFrame(rows, STAGE_COST)
