"""Measures over traces, latencies, shares and codes."""

from __future__ import annotations

import time
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def elapsed(epoch_times: DataFrame, offset: Column, by: list[str]) -> DataFrame:
    """``epoch_times`` (``by``, ``epoch``, ``seconds``) with ``elapsed_s``: offset and running sum."""
    w = Window.partitionBy(*by).orderBy("epoch").rowsBetween(Window.unboundedPreceding, 0)
    return epoch_times.withColumn("elapsed_s", offset + F.sum("seconds").over(w))


def accuracy(predicted: DataFrame, by: list[str]) -> DataFrame:
    """``(by, n, hits)`` of rows with ``predicted`` and ``cls``."""
    return predicted.groupBy(*by).agg(F.count("*").alias("n"), F.sum((F.col("predicted") == F.col("cls")).cast("long")).alias("hits"))


def time_to_accuracy(trace: DataFrame, target: Column, by: list[str]) -> DataFrame:
    """First elapsed time at the target; null if it is never reached."""
    return trace.groupBy(*by).agg(F.min(F.when(F.col("accuracy") >= target, F.col("elapsed_s"))).alias("reached_s"))


def speedup(reached: DataFrame, scheme: str, reference: str, by: list[str]) -> DataFrame:
    """Time of the reference over the time of the scheme, for equal ``by``."""
    a = reached.where(F.col("scheme") == scheme).select(*by, "alpha", F.col("reached_s").alias("own_s"))
    b = reached.where(F.col("scheme") == reference).select(*by, F.col("reached_s").alias("reference_s"))
    return a.join(b, by).withColumn("speedup", F.col("reference_s") / F.col("own_s"))


def choose_alpha(reached: DataFrame, by: list[str]) -> DataFrame:
    """The alpha with the least time for each target; the smaller one of equals, null if none reaches it."""
    return reached.groupBy(*by).agg(F.min(F.when(F.col("reached_s").isNotNull(), F.struct("reached_s", "alpha"))).alias("x")).select(*by, "x.alpha", "x.reached_s")


def retrieval_error(cells: DataFrame) -> DataFrame:
    """``(mode, cells, wraps, wrong, max_ulp)`` of ``(mode, wrapped, diff)``; off by more than one unit is wrong."""
    return cells.groupBy("mode").agg(F.count("*").alias("cells"), F.sum(F.col("wrapped").cast("long")).alias("wraps"), F.sum((F.abs("diff") > 1).cast("long")).alias("wrong"), F.max(F.abs("diff")).alias("max_ulp"))


def chi_square(buckets: DataFrame) -> float:
    """Statistic of bucket counts against the uniform law."""
    n = np.array([r["n"] for r in buckets.collect()], float)  # one row for each bucket
    return float(((n - n.mean()) ** 2 / n.mean()).sum())


def share_correlation(pairs: DataFrame) -> DataFrame:
    """Correlation of secrets and their shares."""
    return pairs.agg(F.corr(F.col("secret").cast("double"), F.col("share").cast("double")).alias("correlation"), F.count("*").alias("n"))


def engine_measures(spark: SparkSession, label: str, action) -> dict:
    """What ``action()`` cost the engine: wall seconds, tasks, task seconds, MB read from files and shuffled, from Spark's own stage records."""
    group = f"{label}-{uuid.uuid4().hex}"
    sc = spark.sparkContext
    sc.setJobGroup(group, label)
    began = time.time()
    try:
        action()
    finally:
        wall = time.time() - began
        sc.setLocalProperty("spark.jobGroup.id", None)
    out = {"step": label, "wall_s": wall, "tasks": 0, "task_s": 0.0, "input_mb": 0.0, "shuffle_mb": 0.0}
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    for job in tracker.getJobIdsForGroup(group):
        for stage in tracker.getJobInfo(job).stageIds:
            if (info := tracker.getStageInfo(stage)) is None or not info.numCompletedTasks:
                continue  # skipped: its output was there already
            data = store.lastStageAttempt(stage)
            out["tasks"] += info.numCompletedTasks
            out["task_s"] += data.executorRunTime() / 1e3
            out["input_mb"] += data.inputBytes() / 1e6
            out["shuffle_mb"] += data.shuffleWriteBytes() / 1e6
    return out


def optimum_gap(theta: np.ndarray, best: np.ndarray) -> float:
    """Frobenius distance to the closed form."""
    return float(np.linalg.norm(theta - best))
