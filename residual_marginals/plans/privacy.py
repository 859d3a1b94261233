"""Zero-concentrated privacy: ledger, conversions, exponential mechanism."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.operators.noise import keyed_gumbel, secret_gumbel


class BudgetExceeded(ValueError):
    """A step would take the total beyond the budget."""


@dataclass
class Ledger:
    """Privacy spent so far; refuses any step past the budget, before its noise is drawn."""

    budget: float
    rows: list[tuple[int, str, float, str]] = field(default_factory=list)
    _parts: list[float] = field(default_factory=list, repr=False)
    _summed: int = field(default=0, repr=False)

    @property
    def total(self) -> float:
        """Exact sum of the charges, rounded once; only rows that came since the last call are added."""
        for _, _, x, _ in self.rows[self._summed :]:
            parts = []
            for y in self._parts:
                if abs(x) < abs(y):
                    x, y = y, x
                high = x + y
                if low := y - (high - x):
                    parts.append(low)
                x = high
            self._parts = [*parts, x]
        self._summed = len(self.rows)
        return math.fsum(self._parts)

    @property
    def left(self) -> float:
        return max(0.0, self.budget - self.total)

    def spend(self, kind: str, rho: float, note: str = "") -> None:
        """Charge what a step costs; callers fit the noise to what is left, never the charge."""
        if rho < 0 or self.total + rho > self.budget * (1 + 1e-12):
            raise BudgetExceeded(f"{kind} needs {rho}, {self.left} is left")
        self.rows.append((len(self.rows), kind, rho, note))

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "step int, kind string, rho double, note string")


def gaussian_rho(sigma2: float) -> float:
    """Cost of isotropic noise on one marginal."""
    return 1 / (2 * sigma2)


def delta_of(rho: float, eps: float) -> float:
    """Least delta of rho-zCDP at eps, over the Renyi orders."""
    orders = 1 + np.logspace(-4, 8, 6000)
    logs = (orders - 1) * (orders * rho - eps) - np.log(orders - 1) + orders * np.log1p(-1 / orders)
    return float(np.exp(min(0.0, logs.min())))


def rho_to_eps(rho: float, delta: float, method: str = "tight") -> float:
    simple = rho + 2 * math.sqrt(rho * math.log(1 / delta))
    if method == "simple":
        return simple
    low, high = 0.0, simple
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (low, mid) if delta_of(rho, mid) <= delta else (mid, high)
    return high


def eps_to_rho(eps: float, delta: float, method: str = "tight") -> float:
    low, high = 0.0, max(eps, 1.0)
    while rho_to_eps(high, delta, method) < eps:
        high *= 2
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if rho_to_eps(mid, delta, method) <= eps else (low, mid)
    return low


def exp_rho(eps: float) -> float:
    """Cost of one exponential-mechanism selection."""
    return eps * eps / 8


def exp_select(scores: DataFrame, eps: float, sensitivity: float, key: str) -> DataFrame:
    """One row (gamma, score, noisy): the exponential mechanism by keyed Gumbel noise, ties to the smaller gamma."""
    noisy = F.col("score") * (eps / (2 * sensitivity)) + keyed_gumbel(key, F.col("gamma"))
    best = F.max_by(F.struct("gamma", "score", "noisy"), F.struct("noisy", -F.col("gamma")))
    return scores.withColumn("noisy", noisy).agg(best.alias("b")).select("b.gamma", "b.score", "b.noisy")


def exp_select_local(scores: dict[int, float], eps: float, sensitivity: float, secret: bytes, key: str, k: int = 1) -> list[int]:
    """k different sets by k exponential mechanisms in a row: the greatest sums of scaled score and one Gumbel draw each. Costs k times ``exp_rho(eps)``."""
    masks = sorted(scores)
    noisy = np.array([scores[m] for m in masks]) * (eps / (2 * sensitivity)) + secret_gumbel(secret, key, len(masks))
    return [masks[j] for j in np.argsort(-noisy, kind="stable")[:k].tolist()]
