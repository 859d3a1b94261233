"""Adaptive release: select a marginal, plan its residuals' noise from what is known, measure, update what changed.

Two states. Local: the true tables were tabulated by one Spark job and all further work is on driver arrays; for
domains whose tables fit there. Cluster: tables stay packed blocks on the executors, and a round is one narrow
pass that scores and one that adds the broadcast changes and stores the blocks. Neither depends on the number of records after tabulation.
True tables never leave this module; annealing and stopping read released values only. Noise needs a secret that only the publisher
knows; who has it can take the noise off, so there is no default.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.domain import Domain, decode, encode
from residual_marginals.lattice import Workload, subsets
from residual_marginals.operators import blocks, lazy, residuals
from residual_marginals.operators.measure import noisy_residual
from residual_marginals.operators.noise import PublicNoise, secret_normal
from residual_marginals.operators.tabulate import collect_blocks, tabulate
from residual_marginals.plans import planner
from residual_marginals.plans.privacy import Ledger, exp_rho, exp_select_local
from residual_marginals.plans.schedule import Schedule
from residual_marginals.sources.io import cut, exists, resume, save_release

TRACE = "round int, gamma long, sigma2 double, epsilon double, rho_used double, n_measured int, n_skipped int, n_touched long, moved_l1 double, seconds double"


@dataclass
class State:
    """Residual estimates with precisions, and the workload's marginals built from them."""

    domain: Domain
    sets: list[int]
    estimates: dict[int, np.ndarray] = field(default_factory=dict)
    precision: dict[int, float] = field(default_factory=dict)
    marginals: dict[int, np.ndarray] = field(default_factory=dict)
    block_updates: int = 0
    holders: dict[int, list[int]] = field(default_factory=dict)

    def holding(self, tau: int) -> list[int]:
        """The wanted sets that contain tau, from lists per attribute."""
        if tau not in self.holders:
            if not self.holders:
                self.holders[0] = list(self.sets)
                for g in self.sets:
                    for i in self.domain.axes(g):
                        self.holders.setdefault(1 << i, []).append(g)
            near = min((self.holders.get(1 << i, []) for i in self.domain.axes(tau)), key=len, default=self.sets)
            self.holders[tau] = [g for g in near if tau & g == tau]
        return self.holders[tau]

    def observe(self, tau: int, z: np.ndarray, sigma2: float) -> np.ndarray:
        """Average a measurement in; returns the change of the estimate."""
        before, weight = self.estimates.get(tau), self.precision.get(tau, 0.0)
        after = z if before is None else (weight * before + z / sigma2) / (weight + 1 / sigma2)
        self.estimates[tau], self.precision[tau] = after, weight + 1 / sigma2
        return after if before is None else after - before

    def rebuild(self) -> None:
        """Every marginal anew, one component per residual."""
        for g in self.sets:
            total = np.zeros(self.domain.shape(g))
            for tau in subsets(g):
                if tau in self.estimates:
                    total += residuals.narrow_component(self.estimates[tau], self.domain, tau, g)
                    self.block_updates += 1
            self.marginals[g] = total

    def build(self) -> None:
        """Every marginal anew through residual coordinates."""
        self.marginals = {g: residuals.assemble(self.estimates, self.domain, g) for g in self.sets}

    def update(self, changes: dict[int, np.ndarray]) -> None:
        """Only marginals that contain a changed residual."""
        for t, d in changes.items():
            # a change is centred once, and then added to each marginal along the axes that it has
            centred = blocks.center_all(d)
            for g in self.holding(t):
                self.marginals[g] = self.marginals[g] + residuals.widened(centred, self.domain, t, g)
                self.block_updates += 1

    def answer(self, mask: int) -> np.ndarray:
        """Marginal of any set: from residuals known for its subsets."""
        return self.marginals[mask] if mask in self.marginals else residuals.assemble(self.estimates, self.domain, mask)


@dataclass
class Release:
    """What a mechanism gives out."""

    domain: Domain
    state: State
    ledger: Ledger
    rounds: list[tuple]

    def marginals(self, spark: SparkSession, gamma: int | None = None) -> DataFrame:
        """(gamma, cell, value, sd), or one marginal with its codes and labels."""
        rows = []
        for g in [gamma] if gamma is not None else self.state.sets:
            sd = math.sqrt(planner.expected_mse(g, self.domain, self.state.precision))
            values = self.state.answer(g).ravel()
            rows.append(pd.DataFrame({"gamma": g, "cell": np.arange(len(values)), "value": values, "sd": sd}))
        out = spark.createDataFrame(pd.concat(rows), "gamma long, cell long, value double, sd double")
        return decode(out, self.domain, gamma) if gamma is not None else out

    def estimates(self, spark: SparkSession) -> DataFrame:
        rows = [pd.DataFrame({"tau": t, "precision": self.state.precision[t], "cell": np.arange(z.size), "value": z.ravel()}) for t, z in self.state.estimates.items()]
        return spark.createDataFrame(pd.concat(rows), "tau long, precision double, cell long, value double")

    def trace(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rounds, TRACE)


class ScoreCache:
    """L1 distances between true and estimated marginals; only those that a changed residual reaches are computed again."""

    def __init__(self, state: State, truth: dict[int, np.ndarray], candidates: list[int]):
        self.state, self.truth, self.candidates = state, truth, candidates
        self.l1: dict[int, float] = {}
        self.changed: set[int] | None = None
        self.computed = 0

    def note(self, taus) -> None:
        if self.changed is not None:
            self.changed |= set(taus)

    def refresh(self) -> dict[int, float]:
        for g in self.candidates:
            if self.changed is None or any(t & g == t for t in self.changed):
                self.l1[g] = float(np.abs(self.truth[g] - self.state.answer(g)).sum())
                self.computed += 1
        self.changed = set()
        return self.l1


def save_progress(spark: SparkSession, release: Release, path: str) -> None:
    """Store what is released so far: estimates, ledger, trace."""
    save_release({"estimates": release.estimates(spark), "ledger": release.ledger.to_df(spark), "trace": release.trace(spark)}, path)


def load_progress(spark: SparkSession, path: str, domain: Domain, workload: Workload, budget: float) -> Release:
    """A stored release, ready to go on with ``adaptive_release(..., progress=...)``."""
    state, ledger = State(domain, list(workload.sets)), Ledger(budget)
    for tau, own in resume(spark, path, "estimates").toPandas().groupby("tau"):
        own = own.sort_values("cell")
        state.estimates[int(tau)] = own["value"].to_numpy().reshape([n - 1 for n in domain.shape(int(tau))])
        state.precision[int(tau)] = float(own["precision"].iloc[0])
    state.build()
    for r in resume(spark, path, "ledger").orderBy("step").collect():
        ledger.spend(r["kind"], r["rho"], r["note"])
    return Release(domain, state, ledger, [tuple(r) for r in resume(spark, path, "trace").orderBy("round").collect()])


def candidate_weights(candidates: list[int], workload: Workload) -> dict[int, float]:
    """How much each candidate overlaps the weighted workload."""
    return {g: sum(c * (s & g).bit_count() for s, c in zip(workload.sets, workload.weights)) for g in candidates}


def init_one_way(state: State, truth: dict[int, np.ndarray], sigma2: float, ledger: Ledger, secret: bytes | PublicNoise, key: str, rho_each: float | None = None) -> None:
    """Measure every 1-way marginal; each also measures the total."""
    ones = [1 << i for i in range(len(state.domain)) if any(s >> i & 1 for s in state.sets)]
    for g in ones:
        ledger.spend("one-way", rho_each if rho_each is not None else 1 / (2 * sigma2), state.domain.names(g)[0])
        noise = secret_normal(secret, f"{key}:init:{g}", truth[g].size).reshape(truth[g].shape)
        for tau, z in residuals.split(truth[g] + math.sqrt(sigma2) * noise, state.domain, g).items():
            state.observe(tau, z, sigma2 * (state.domain.size(g) if tau == 0 else 1))
    state.build()


def measure_plan(state: State, truth: dict[int, np.ndarray], plan: list[planner.Row], secret: bytes | PublicNoise, key: str) -> dict[int, np.ndarray]:
    """Measure the kept residuals of a plan; returns the changes of their estimates."""
    changes = {}
    for row in plan:
        if row.keep and row.new > 0:
            t = truth[row.tau]
            z = noisy_residual(t, state.domain, row.tau, row.sigma2, secret_normal(secret, f"{key}:{row.tau}", t.size))
            changes[row.tau] = state.observe(row.tau, z, row.sigma2)
    return changes


def _plan(planner_name: str, gamma: int, state: State, rho: float, min_gain: float) -> list[planner.Row]:
    if planner_name == "iid":
        return planner.iid_plan(gamma, state.domain, rho)
    if planner_name == "conditional":
        return planner.conditional_plan(gamma, state.domain, state.precision, rho, min_gain)
    raise ValueError("planner must be conditional or iid")


def adaptive_release(
    df: DataFrame | None, domain: Domain, workload: Workload, rho: float, *, planner_name: str = "conditional", update: str = "lazy", secret: bytes | PublicNoise, key: str = "run",
    max_rounds: int | None = None, sequence: list[int] | None = None, split: float = 0.5, rounds_per_score: int = 1, min_gain: float = 1e-3, truth: dict[int, np.ndarray] | None = None, progress: Release | None = None,
) -> Release:
    """Release the workload under rho-zCDP.

    ``sequence`` fixes the marginals and their order (then ``split`` of the budget goes to 1-way marginals and the rest evenly
    to the sequence); otherwise each round selects one from the whole closure by the exponential mechanism on the
    expected improvement. ``rounds_per_score`` different marginals may be selected, and paid for, on the same scores. ``truth`` skips tabulation when runs share one; ``progress`` goes on
    from an earlier release of the same data, whose rounds keep their numbers, so that no noise is drawn twice.
    """
    closed = workload.closure()
    if truth is None:
        truth = collect_blocks(tabulate(encode(df, domain), domain, closed, dense=False), domain, closed)
    state, ledger, rounds = (progress.state, progress.ledger, list(progress.rounds)) if progress else (State(domain, list(workload.sets)), Ledger(rho), [])
    if progress:
        ledger.budget = rho
    apply = state.update if update == "lazy" else lambda _: state.rebuild()

    cache: ScoreCache | None = None

    def step(k: int, gamma: int, spend: float, eps: float) -> float:
        """Measure with noise that costs ``spend``."""
        began, before = time.perf_counter(), state.answer(gamma).copy()
        plan = _plan(planner_name, gamma, state, spend, min_gain)
        ledger.spend("measure", spend, str(gamma))
        already = state.block_updates
        if planner_name == "iid":
            noise = secret_normal(secret, f"{key}:{k}:{gamma}", truth[gamma].size).reshape(truth[gamma].shape)
            noisy = residuals.split(truth[gamma] + noise / math.sqrt(2 * spend), domain, gamma)
            changes = {x.tau: state.observe(x.tau, noisy[x.tau], x.sigma2) for x in plan}
        else:
            changes = measure_plan(state, truth, plan, secret, f"{key}:{k}")
        if update == "lazy" and planner_name == "iid":
            # the ablation's baseline: one residual at a time
            for t, d in changes.items():
                state.update({t: d})
        else:
            apply(changes)
        if cache is not None:
            cache.note(changes)
        moved = float(np.abs(state.answer(gamma) - before).sum())
        rounds.append((k, gamma, 1 / (2 * spend), eps, ledger.total, len(changes), len(plan) - len(changes), state.block_updates - already, moved, time.perf_counter() - began))
        return moved

    if sequence is not None:
        d = sum(any(s >> i & 1 for s in closed) for i in range(len(domain)))
        init_one_way(state, truth, d / (2 * rho * split), ledger, secret, key)
        each = rho * (1 - split) / len(sequence)
        for k, gamma in enumerate(sequence):
            step(k, gamma, min(each, ledger.left), 0.0)
        return Release(domain, state, ledger, rounds)

    candidates = [g for g in closed if g]
    weights = candidate_weights(candidates, workload)
    sensitivity = max(weights.values())
    schedule = Schedule.initial(rho, len(closed))
    if not progress:
        init_one_way(state, truth, schedule.sigma**2, ledger, secret, key)
    cache = ScoreCache(state, truth, candidates)
    k = rounds[-1][0] + 1 if rounds else 0
    picked: list[int] = []
    while ledger.left > rho * 1e-9 and (max_rounds is None or k < max_rounds):
        if not picked:
            schedule.fit(ledger.left)
            noise = math.sqrt(2 / math.pi) * schedule.sigma
            scores = {g: weights[g] * (l1 - noise * domain.size(g)) for g, l1 in cache.refresh().items()}
            many = max(1, min(rounds_per_score, len(scores), int(ledger.left / schedule.round_rho)))
            for _ in range(many):
                ledger.spend("select", exp_rho(schedule.epsilon))
            picked = exp_select_local(scores, schedule.epsilon, sensitivity, secret, f"{key}:select:{k}", many)
            selected_with = schedule.epsilon
        gamma = picked.pop(0)
        moved = step(k, gamma, min(1 / (2 * schedule.sigma**2), ledger.left), selected_with)
        schedule.anneal(moved, domain.size(gamma))
        k += 1
    return Release(domain, state, ledger, rounds)


def score_blocks(true_blocks: DataFrame, estimated: DataFrame, domain: Domain, weights: dict[int, float], sigma: float) -> DataFrame:
    """(gamma, score) on the cluster: co-partitioned packed blocks, one row per candidate."""
    a = true_blocks.select("gamma", F.col("values").alias("t"))
    b = estimated.select("gamma", F.col("values").alias("e"))
    gap = F.aggregate(F.zip_with("t", "e", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)
    w = true_blocks.sparkSession.createDataFrame([(g, float(x), float(domain.size(g))) for g, x in weights.items()], "gamma long, w double, n double")
    return a.join(b, "gamma").join(F.broadcast(w), "gamma").select("gamma", (F.col("w") * (gap - math.sqrt(2 / math.pi) * sigma * F.col("n"))).alias("score"))


def adaptive_release_cluster(df: DataFrame, domain: Domain, workload: Workload, rho: float, *, secret: bytes | PublicNoise, key: str = "run", max_rounds: int | None = None, min_gain: float = 1e-3, store: str | None = None):
    """The same loop with all tables on the executors, until the budget is spent: (marginals as packed blocks, ledger, trace rows).

    Per round one job scores (co-partitioned by gamma) and one fetches the chosen marginal's block; changes are broadcast
    to the blocks that contain them, and the blocks are stored anew, so no round repeats the work of those before it. With ``store`` (a folder)
    what was released is stored after every round, and a call with the same arguments goes on from there; rounds keep
    their numbers, so no noise is drawn twice.
    """
    spark, closed = df.sparkSession, workload.closure()
    candidates = [g for g in closed if g]
    cells = tabulate(encode(df, domain), domain, closed)
    true_blocks = cut(residuals.pack(cells).repartition("gamma"))
    zero = true_blocks.select("gamma", "kind", F.transform("values", lambda v: v * 0.0).alias("values"))
    schedule, weights = Schedule.initial(rho, len(closed)), candidate_weights(candidates, workload)
    if store and exists(spark, f"{store}/done"):
        progress = load_progress(spark, f"{store}/{_last_round(spark, store)}", domain, Workload([]), rho)
        state, ledger, trace = progress.state, progress.ledger, progress.rounds
        schedule.replay(trace, domain)
    else:
        ones = {r["gamma"]: np.array(r["values"]) for r in true_blocks.where(F.col("gamma").isin([g for g in closed if g.bit_count() <= 1])).collect()}
        state, ledger, trace = State(domain, [g for g in closed if g.bit_count() == 1]), Ledger(rho), []
        init_one_way(state, {g: v.reshape(domain.shape(g)) for g, v in ones.items()}, schedule.sigma**2, ledger, secret, key)
        state.sets = []
    blocks_now = cut(lazy.lazy_round(zero, domain, dict(state.estimates)))
    k = trace[-1][0] + 1 if trace else 0
    while ledger.left > rho * 1e-9 and (max_rounds is None or k < max_rounds):
        began = time.perf_counter()
        schedule.fit(ledger.left)
        scores = {r["gamma"]: r["score"] for r in score_blocks(true_blocks.where("gamma <> 0"), blocks_now, domain, weights, schedule.sigma).collect()}
        ledger.spend("select", exp_rho(schedule.epsilon))
        (gamma,) = exp_select_local(scores, schedule.epsilon, max(weights.values()), secret, f"{key}:select:{k}")
        spend = min(1 / (2 * schedule.sigma**2), ledger.left)
        plan = planner.conditional_plan(gamma, domain, state.precision, spend, min_gain)
        ledger.spend("measure", spend, str(gamma))
        own = [x.tau for x in plan if x.keep and x.new > 0]
        truth = {r["gamma"]: np.array(r["values"]).reshape(domain.shape(r["gamma"])) for r in true_blocks.where(F.col("gamma").isin(own)).collect()}
        before = residuals.assemble(state.estimates, domain, gamma)
        changes = measure_plan(state, truth, plan, secret, f"{key}:{k}")
        moved = float(np.abs(residuals.assemble(state.estimates, domain, gamma) - before).sum())
        blocks_now = cut(lazy.lazy_round(blocks_now, domain, changes))
        reached = sum(any(t & g == t for t in changes) for g in closed)
        trace.append((k, gamma, 1 / (2 * spend), schedule.epsilon, ledger.total, len(own), len(plan) - len(own), reached, moved, time.perf_counter() - began))
        if store:
            save_progress(spark, Release(domain, state, ledger, trace), f"{store}/round-{k:06d}")
            spark.createDataFrame([(k,)], "round int").write.mode("append").parquet(f"{store}/done")
        schedule.anneal(moved, domain.size(gamma))
        k += 1
    return blocks_now.where(F.col("gamma").isin(workload.sets)), ledger, trace


def _last_round(spark: SparkSession, store: str) -> str:
    """Folder of the last round that was stored whole."""
    return f"round-{resume(spark, store, 'done').agg(F.max('round')).first()[0]:06d}"
