"""One-shot and dense baselines."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame

from residual_marginals.domain import Domain, encode
from residual_marginals.lattice import Workload
from residual_marginals.mechanisms.adaptive import Release, State, measure_plan
from residual_marginals.operators.noise import PublicNoise, discrete_gaussian, secret_gumbel, secret_normal
from residual_marginals.operators.tabulate import collect_blocks, tabulate
from residual_marginals.plans import planner
from residual_marginals.plans.privacy import Ledger, exp_rho


def truth_of(df: DataFrame, domain: Domain, workload: Workload) -> dict[int, np.ndarray]:
    """Exact tables of the workload's closure, as driver arrays; for the trusted side only."""
    closed = workload.closure()
    return collect_blocks(tabulate(encode(df, domain), domain, closed, dense=False), domain, closed)


def batch_release(df: DataFrame | None, domain: Domain, workload: Workload, rho: float, *, objective: str = "sum", per_cell: bool = True, secret: bytes | PublicNoise, key: str = "batch", truth=None) -> Release:
    """The optimal one-shot plan: each residual of the closure once, then one reconstruction."""
    truth = truth_of(df, domain, workload) if truth is None else truth
    state, ledger = State(domain, list(workload.sets)), Ledger(rho)
    plan = planner.batch_plan(workload, domain, rho, per_cell, objective)
    ledger.spend("batch", planner.residual_rho(plan))
    measure_plan(state, truth, plan, secret, key)
    state.build()
    return Release(domain, state, ledger, [])


def direct_release(df: DataFrame | None, domain: Domain, workload: Workload, rho: float, *, split: str = "even", integer: bool = False, secret: bytes | PublicNoise, key: str = "direct", truth=None) -> tuple[dict[int, np.ndarray], Ledger]:
    """Noise on every wanted marginal by itself; the answers do not agree with each other. ``split``: even, or by_size (cube root of the cells).

    ``integer``: discrete Gaussian noise of the same cost, so counts stay whole.
    """
    truth = truth_of(df, domain, workload) if truth is None else truth
    ledger = Ledger(rho)
    share = {g: 1.0 if split == "even" else domain.size(g) ** (1 / 3) for g in workload.sets}
    total, out = sum(share.values()), {}
    for g in workload.sets:
        cost = rho * share[g] / total
        ledger.spend("direct", cost, str(g))
        scale, n = 1 / math.sqrt(2 * cost), truth[g].size
        noise = discrete_gaussian(secret, f"{key}:{g}", scale, n) if integer else scale * secret_normal(secret, f"{key}:{g}", n)
        out[g] = truth[g] + noise.reshape(truth[g].shape)
    return out, ledger


def identity_strategy(full: np.ndarray, domain: Domain, sets: list[int], rho: float, *, secret: bytes | PublicNoise, key: str = "identity") -> tuple[dict[int, np.ndarray], Ledger]:
    """Noise on every cell of the whole domain, then sums; for domains small enough to hold."""
    ledger = Ledger(rho)
    ledger.spend("identity", rho)
    noisy = full + secret_normal(secret, key, full.size).reshape(full.shape) / math.sqrt(2 * rho)
    return {g: noisy.sum(axis=tuple(i for i in range(len(domain)) if not g >> i & 1)) for g in sets}, ledger


def multiplicative_weights(
    full: np.ndarray, domain: Domain, sets: list[int], rho: float, *, rounds: int = 20, passes: int = 10, total_share: float = 0.05, secret: bytes | PublicNoise, key: str = "mw"
) -> tuple[dict[int, np.ndarray], Ledger]:
    """Early adaptive method on the dense data vector: select the worst marginal, measure it, reweight every cell.

    The number of records, which the estimate is scaled to, is measured too, with ``total_share`` of the budget.
    """
    ledger = Ledger(rho)
    ledger.spend("total", rho * total_share)
    total = max(1.0, float(full.sum() + secret_normal(secret, f"{key}:total", 1)[0] / math.sqrt(2 * rho * total_share)))
    estimate = np.full(full.shape, total / full.size)
    rest = {g: tuple(i for i in range(len(domain)) if not g >> i & 1) for g in sets}
    each, kept = rho * (1 - total_share) / rounds, []
    for k in range(rounds):
        gaps = np.array([np.abs(full.sum(axis=rest[g]) - estimate.sum(axis=rest[g])).sum() - math.sqrt(2 / math.pi) / math.sqrt(each) * domain.size(g) for g in sets])
        eps = math.sqrt(4 * each)
        ledger.spend("select", exp_rho(eps))
        g = sets[int(np.argmax(gaps * eps / 2 + secret_gumbel(secret, f"{key}:{k}", len(sets))))]
        ledger.spend("measure", each / 2, str(g))
        truth = full.sum(axis=rest[g])
        kept.append((g, truth + secret_normal(secret, f"{key}:{k}:{g}", truth.size).reshape(truth.shape) / math.sqrt(each)))
        for _ in range(passes):
            for h, y in kept:
                step = (y - estimate.sum(axis=rest[h])) / (2 * total)
                estimate = estimate * np.exp(np.clip(step.reshape([n if h >> i & 1 else 1 for i, n in enumerate(full.shape)]), -1, 1))
                estimate *= total / estimate.sum()
    return {g: estimate.sum(axis=rest[g]) for g in sets}, ledger
