"""The experiment workloads on the given tables: transform timing, ablation, error against time."""

from __future__ import annotations

import random
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals import measures
from residual_marginals.domain import Domain
from residual_marginals.lattice import Workload
from residual_marginals.mechanisms import baselines, graphical
from residual_marginals.mechanisms.adaptive import adaptive_release
from residual_marginals.operators import blocks, tiles
from residual_marginals.operators.axisops import AxisProgram, kron_cells
from residual_marginals.plans.privacy import eps_to_rho

RUNS = "dataset string, method string, eps double, trial int, seconds double, l1 double, rho double, updates long, skipped double"
TIMES = "impl string, op string, degree int, n int, seconds double, cells long, steps long"

STRATEGIES = {"lazy_conditional": ("conditional", "lazy"), "lazy_iid": ("iid", "lazy"), "full_iid": ("iid", "full")}


def run_transform_bench(spark: SparkSession, shapes: list[tuple[int, int]], repeats: int = 5, relational_cells: int = 5000) -> DataFrame:
    """Own-marginal decomposition and reconstruction of (degree, axis length) arrays: in-axis against explicit factors.

    Small arrays are also run as relations.
    """
    rows = []
    for degree, n in shapes:
        shape, keep = (n,) * degree, tuple(range(degree))
        array = np.random.default_rng(degree * 1000 + n).random(shape)
        residual = blocks.decompose(array, keep)
        axes = [f"a{k}" for k in range(degree)]
        down, up = AxisProgram.decompose(axes, shape, axes), AxisProgram.reconstruct(axes, shape, axes)
        there, back = blocks.factors(shape, keep), blocks.factors(shape, keep, inverse=True)
        runs = {
            ("in_axis", "decompose"): lambda: down.compile_block(array),
            ("in_axis", "reconstruct"): lambda: up.compile_block(residual),
            ("kron", "decompose"): lambda: blocks.kron_by_axis(array, there),
            ("kron", "reconstruct"): lambda: blocks.kron_by_axis(residual, back),
        }
        if array.size <= 20 * relational_cells:
            def mapped(block=array):
                for k in keep:
                    block = blocks.axis_sub_mapped(block, k)
                return block

            runs["mapped", "decompose"] = mapped
        if array.size <= relational_cells:
            rest, cells = F.col("id"), {}
            for a in reversed(axes):
                cells[a] = (rest % n).cast("int").alias(a)
                rest = F.floor(rest / n)
            frame = spark.range(array.size).select(*cells.values(), F.xxhash64("id").cast("double").alias("value"))
            runs["cells", "decompose"] = lambda: measures.force(down.compile_cells(frame))
            runs["cells_kron", "decompose"] = lambda: measures.force(kron_cells(frame, axes, dict(zip(axes, there))))
        for (impl, op), run in runs.items():
            run()
            seconds, _ = measures.time_trials(run, repeats if "cells" not in impl else 1)
            rows.append((impl, op, degree, n, seconds, array.size, down.op_count() if op == "decompose" else up.op_count()))
    return spark.createDataFrame(rows, TIMES)


def run_tiled_bench(spark: SparkSession, shapes: list[tuple[int, int]]) -> DataFrame:
    """(op, degree, n, seconds, cells): decomposition and reconstruction of arrays of any size as tiles on the executors."""
    rows = []
    for degree, n in shapes:
        shape, keep = (n,) * degree, tuple(range(degree))
        array = tiles.generated(spark, shape, lambda cell: F.pmod(F.xxhash64(cell), F.lit(1000)))
        for op in ("decompose", "both"):
            out = tiles.decompose(array, shape, keep)
            seconds, _ = measures.time_trials(lambda out=out if op == "decompose" else tiles.reconstruct(out, shape, keep): measures.force(out), 1)
            rows.append((op, degree, n, seconds, n**degree))
    return spark.createDataFrame(rows, "op string, degree int, n int, seconds double, cells long")


def transform_speedups(times: DataFrame) -> DataFrame:
    """(op, degree, n, speedup) of in-axis steps over explicit factors."""
    wide = times.groupBy("op", "degree", "n").agg(F.avg(F.when(F.col("impl") == "kron", F.col("seconds"))).alias("k"), F.avg(F.when(F.col("impl") == "in_axis", F.col("seconds"))).alias("a"))
    return wide.select("op", "degree", "n", (F.col("k") / F.col("a")).alias("speedup"))


def fixed_sequence(workload: Workload, seed: int = 0) -> list[int]:
    order = list(workload.sets)
    random.Random(seed).shuffle(order)
    return order


def run_ablation(spark: SparkSession, data: dict[str, tuple[DataFrame, Domain]], *, secret: bytes, k: int = 3, eps: float = 1.0, delta: float = 1e-9, trials: int | dict[str, int] = 5, strategies: list[str] | None = None) -> DataFrame:
    """Given sequences of k-way marginals, half the budget on 1-way marginals: time, error and block updates per strategy.

    ``trials``: for all strategies, or by strategy.
    """
    rows, rho = [], eps_to_rho(eps, delta)
    for name, (df, domain) in data.items():
        workload = Workload.all_kway(domain, k)
        truth = baselines.truth_of(df, domain, workload)
        for strategy in strategies or STRATEGIES:
            plan, update = STRATEGIES[strategy]
            for trial in range(trials[strategy] if isinstance(trials, dict) else trials):
                began = time.perf_counter()
                out = adaptive_release(None, domain, workload, rho, secret=secret, planner_name=plan, update=update, sequence=fixed_sequence(workload), key=f"trial{trial}", truth=truth)
                seconds = time.perf_counter() - began
                error = measures.local_l1(truth, out.state.marginals, workload.sets)
                asked = sum(r[5] + r[6] for r in out.rounds)
                rows.append((name, strategy, eps, trial, seconds, error, out.ledger.total, out.state.block_updates, sum(r[6] for r in out.rounds) / asked))
    return spark.createDataFrame(rows, RUNS).withColumnRenamed("method", "strategy")


def run_tradeoff(spark: SparkSession, data: dict[str, tuple[DataFrame, Domain]], eps_grid: list[float], methods: list[str], *, secret: bytes, k: int = 3, delta: float = 1e-9, trials: int | dict[str, int] = 5, model_mb: float = 50.0) -> DataFrame:
    """Error and time of whole mechanisms on all k-way marginals over budgets; one tabulation is shared by all runs on a data set.

    ``trials``: for all methods, or by method.
    """
    rows = []
    for name, (df, domain) in data.items():
        workload = Workload.all_kway(domain, k)
        truth = baselines.truth_of(df, domain, workload)
        for eps in eps_grid:
            rho = eps_to_rho(eps, delta)
            for method in methods:
                for trial in range(trials[method] if isinstance(trials, dict) else trials):
                    key, began = f"{method}{trial}", time.perf_counter()
                    updates = 0
                    if method == "adaptive":
                        out = adaptive_release(None, domain, workload, rho, secret=secret, key=key, truth=truth)
                        answers, spent, updates = out.state.marginals, out.ledger.total, out.state.block_updates
                    elif method == "batch":
                        out = baselines.batch_release(None, domain, workload, rho, secret=secret, key=key, truth=truth)
                        answers, spent = out.state.marginals, out.ledger.total
                    elif method == "direct":
                        answers, ledger = baselines.direct_release(None, domain, workload, rho, secret=secret, key=key, truth=truth)
                        spent = ledger.total
                    elif method == "graphical":
                        answers, ledger = graphical.adaptive_graphical(truth, domain, workload, rho, model_mb=model_mb, secret=secret, key=key)
                        spent = ledger.total
                    else:
                        raise ValueError(method)
                    rows.append((name, method, eps, trial, time.perf_counter() - began, measures.local_l1(truth, answers, workload.sets), spent, updates, 0.0))
    return spark.createDataFrame(rows, RUNS)


def size_sweep(spark: SparkSession, df: DataFrame, domain: Domain, sizes_mb: list[float], *, secret: bytes, eps: float = 1.0, k: int = 3) -> DataFrame:
    """The graphical mechanism over model sizes: (model_mb, seconds, l1)."""
    rows = []
    for mb in sizes_mb:
        run = run_tradeoff(spark, {"sweep": (df, domain)}, [eps], ["graphical"], secret=secret, k=k, trials=1, model_mb=mb).first()
        rows.append((float(mb), run["seconds"], run["l1"]))
    return spark.createDataFrame(rows, "model_mb double, seconds double, l1 double")
