"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from residual_marginals.operators import blocks


def _paired(truth: DataFrame, estimate: DataFrame) -> DataFrame:
    a = truth.select("gamma", "cell", F.col("value").cast("double").alias("t"))
    b = estimate.select("gamma", "cell", F.col("value").cast("double").alias("e"))
    return a.join(b, ["gamma", "cell"], "full").select("gamma", "cell", F.coalesce("t", F.lit(0.0)).alias("t"), F.coalesce("e", F.lit(0.0)).alias("e"))


def l1_error(truth: DataFrame, estimate: DataFrame, weights: dict[int, float] | None = None, normalise: str = "none") -> DataFrame:
    """(gamma, l1, n_cells): summed absolute error per marginal; absent cells count as zero.

    ``normalise``: none, records (divide by the marginal's total) or cells. ``weights`` scale marginals.
    """
    out = _paired(truth, estimate).groupBy("gamma").agg(F.sum(F.abs(F.col("t") - F.col("e"))).alias("l1"), F.sum("t").alias("_n"), F.count(F.lit(1)).alias("n_cells"))
    by = {"none": F.lit(1.0), "records": F.col("_n"), "cells": F.col("n_cells")}[normalise]
    out = out.withColumn("l1", F.col("l1") / by).drop("_n")
    if weights:
        w = truth.sparkSession.createDataFrame([(g, float(x)) for g, x in weights.items()], "gamma long, _w double")
        out = out.join(F.broadcast(w), "gamma").withColumn("l1", F.col("l1") * F.col("_w")).drop("_w")
    return out


def workload_error(truth: DataFrame, estimate: DataFrame, **options) -> float:
    """Mean over the workload's marginals of ``l1_error``."""
    return l1_error(truth, estimate, **options).agg(F.avg("l1")).first()[0]


def l2_error(truth: DataFrame, estimate: DataFrame) -> DataFrame:
    """(gamma, sse, mse)."""
    square = (F.col("t") - F.col("e")) ** 2
    return _paired(truth, estimate).groupBy("gamma").agg(F.sum(square).alias("sse"), F.avg(square).alias("mse"))


def local_l1(truth: dict[int, np.ndarray], estimate: dict[int, np.ndarray], sets: list[int]) -> float:
    return float(np.mean([np.abs(truth[g] - estimate[g]).sum() for g in sets]))


def weighted_residual_loss(measured: list[tuple[np.ndarray, float]], estimate: np.ndarray) -> float:
    """Sum over measurements of one residual of the squared error in the inverse covariance norm: the plain norm after centring every axis."""
    return math.fsum(float((blocks.center_all(z - estimate) ** 2).sum()) / s2 for z, s2 in measured)


def time_trials(run: Callable[[], object], trials: int = 5) -> tuple[float, list[float]]:
    """Mean seconds, and each trial's."""
    seconds = []
    for _ in range(trials):
        began = time.perf_counter()
        run()
        seconds.append(time.perf_counter() - began)
    return float(np.mean(seconds)), seconds


def force(df: DataFrame) -> None:
    """Compute every row without keeping any."""
    df.write.format("noop").mode("overwrite").save()


def speedup_table(rows: DataFrame, reference: str) -> DataFrame:
    """(dataset, strategy, speedup, lowest, highest) of (dataset, strategy, trial, seconds) over a reference strategy."""
    mean = rows.groupBy("dataset", "strategy").agg(F.avg("seconds").alias("s"), F.min("seconds").alias("low"), F.max("seconds").alias("high"))
    base = mean.where(F.col("strategy") == reference).select("dataset", F.col("s").alias("_r"))
    return mean.join(base, "dataset").select("dataset", "strategy", (F.col("_r") / F.col("s")).alias("speedup"), (F.col("_r") / F.col("high")).alias("lowest"), (F.col("_r") / F.col("low")).alias("highest"))


def relative_to(rows: DataFrame, method: str = "batch") -> DataFrame:
    """Time and error over those of one method, per dataset and epsilon."""
    base = rows.where(F.col("method") == method).groupBy("dataset", "eps").agg(F.avg("seconds").alias("_s"), F.avg("l1").alias("_e"))
    return rows.groupBy("dataset", "eps", "method").agg(F.avg("seconds").alias("seconds"), F.avg("l1").alias("l1")).join(base, ["dataset", "eps"]).select("dataset", "eps", "method", (F.col("seconds") / F.col("_s")).alias("relative_time"), (F.col("l1") / F.col("_e")).alias("relative_error"))


def plan_costs(df: DataFrame) -> dict[str, int]:
    """Counts of operators in the physical plan: scans, exchanges, broadcasts, Python stages."""
    text = df._jdf.queryExecution().executedPlan().toString()
    # an adaptive plan that has run shows its first plan as well
    text = text.split("+- == Initial Plan ==")[0]
    return {"scans": text.count("FileScan"), "exchanges": text.count("Exchange hash") + text.count("Exchange range"), "broadcasts": text.count("BroadcastExchange"), "python": text.count("MapInPandas") + text.count("MapInArrow") + text.count("ArrowEvalPython")}


COSTS = "jobs int, stages int, tasks long, rows_read long, shuffle_bytes long, spilled_bytes long, executor_seconds double, seconds double"


def spark_costs(spark: SparkSession, run: Callable[[], object]) -> dict[str, float]:
    """What the Spark jobs of ``run`` did: jobs, stages that ran, tasks, rows read, bytes shuffled and spilled, executor and wall time."""
    context, group, began = spark.sparkContext, f"costs-{uuid.uuid4().hex}", time.perf_counter()
    context.setJobGroup(group, "measured")
    try:
        run()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.perf_counter() - began
    context._jsc.sc().listenerBus().waitUntilEmpty()
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    jobs = list(tracker.getJobIdsForGroup(group))
    out = dict.fromkeys(("stages", "tasks", "rows_read", "shuffle_bytes", "spilled_bytes", "executor_seconds"), 0)
    for stage in sorted({s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}):
        data = store.lastStageAttempt(stage)
        if data.numCompleteTasks():
            out["stages"] += 1
            out["tasks"] += data.numCompleteTasks()
            out["rows_read"] += data.inputRecords()
            out["shuffle_bytes"] += data.shuffleWriteBytes()
            out["spilled_bytes"] += data.diskBytesSpilled()
            out["executor_seconds"] += data.executorRunTime() / 1000
    return {"jobs": len(jobs), **out, "seconds": seconds}


def largest_errors(truth: DataFrame, estimate: DataFrame, k: int = 10) -> DataFrame:
    """(gamma, cell, error): the k cells of largest absolute error, ties to the smaller set and cell. For the trusted side only."""
    gap = _paired(truth, estimate).select("gamma", "cell", F.abs(F.col("t") - F.col("e")).alias("error"))
    return gap.orderBy(F.desc("error"), "gamma", "cell").limit(k)


def worst_marginals(truth: DataFrame, estimate: DataFrame, k: int = 5) -> DataFrame:
    """(gamma, l1, n_cells, place, part): the k marginals of largest error, with their rank and the quarter of all marginals that they fall into."""
    order = Window.orderBy(F.desc("l1"), "gamma")
    # a row per marginal
    ranked = l1_error(truth, estimate).withColumn("place", F.row_number().over(order)).withColumn("part", F.ntile(4).over(order))
    return ranked.where(F.col("place") <= k)


def error_profile(truth: DataFrame, estimate: DataFrame) -> DataFrame:
    """(gamma, spread, median, most): standard deviation, approximate median and maximum of the absolute error of the cells."""
    gap = _paired(truth, estimate).select("gamma", F.abs(F.col("t") - F.col("e")).alias("g"))
    return gap.groupBy("gamma").agg(F.stddev_pop("g").alias("spread"), F.percentile_approx("g", 0.5, 1_000_000).alias("median"), F.max("g").alias("most"))


def ledger_rows(spark: SparkSession, ledger, delta: float = 1e-9) -> DataFrame:
    """(total_rho, eps): what a run has spent."""
    from residual_marginals.plans.privacy import rho_to_eps

    return spark.createDataFrame([(ledger.total, rho_to_eps(ledger.total, delta))], "total_rho double, eps double")
