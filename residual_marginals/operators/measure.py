"""Gaussian measurements of marginals and of residuals."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from residual_marginals.domain import Domain
from residual_marginals.operators import residuals
from residual_marginals.operators.noise import keyed_normal


def measure_marginal(cells: DataFrame, domain: Domain, sigma2: float | Column, key: str, round_: int = 0) -> DataFrame:
    """(round, gamma, sigma2, cell, value): isotropic noise on every cell of dense marginals.

    Costs 1 / (2 sigma2) per marginal. Refuses sparse input, as absent cells are private too.
    """
    # a row per set; the check is part of the plan, so measuring starts no job of its own
    full = cells.groupBy("gamma").agg((F.count(F.lit(1)) == other_lengths(domain, F.lit(0).cast("long"))).alias("_full"))
    scale = F.lit(float(sigma2)) if not isinstance(sigma2, Column) else sigma2
    noise = keyed_normal(key, F.lit(round_), F.col("gamma"), F.col("cell"))
    refused = F.raise_error(F.concat(F.lit("marginal "), F.col("gamma").cast("string"), F.lit(" is not dense; use densify first"))).cast("double")
    value = F.when(F.col("_full"), F.col("value") + F.sqrt(scale) * noise).otherwise(refused)
    return cells.join(F.broadcast(full), "gamma").select(F.lit(round_).alias("round"), "gamma", scale.alias("sigma2"), "cell", value.alias("value"))


def other_lengths(domain: Domain, support: Column) -> Column:
    """Product of the lengths of the axes of ``gamma`` outside ``support``."""
    out = F.lit(1.0)
    for i, a in enumerate(domain.attributes):
        bit = F.lit(1 << i).cast("long")
        out = out * F.when((F.col("gamma").bitwiseAND(bit) != 0) & (support.bitwiseAND(bit) == 0), float(a.n)).otherwise(1.0)
    return out


def marginal_to_residuals(measured: DataFrame, domain: Domain) -> DataFrame:
    """(round, gamma, tau, sigma2, cell, value): noisy marginals as noisy residuals, whose variance grows by the lengths of the summed axes."""
    parts = residuals.decompose_all(measured.select("gamma", "round", "sigma2", "cell", "value"), domain, ("round", "sigma2"))
    return parts.select("round", "gamma", "tau", (F.col("sigma2") * other_lengths(domain, F.col("tau"))).alias("sigma2"), "cell", "value")


def measure_residual(cells: DataFrame, domain: Domain, tau: int, sigma2: float, key: str, round_: int = 0) -> DataFrame:
    """(round, tau, sigma2, cell, value): isotropic noise on marginal tau, then its own residual."""
    noisy = measure_marginal(cells.where(F.col("gamma") == tau), domain, sigma2, key, round_).select("gamma", "cell", "value")
    own = residuals.decompose_all(noisy, domain).where(F.col("tau") == tau)
    return own.select(F.lit(round_).alias("round"), "tau", F.lit(float(sigma2)).alias("sigma2"), "cell", "value")


def noisy_residual(truth: np.ndarray, domain: Domain, tau: int, sigma2: float, normal: np.ndarray) -> np.ndarray:
    """The same on the driver, with given standard normals."""
    return residuals.residual_of(truth + np.sqrt(sigma2) * normal.reshape(truth.shape), domain, tau, tau)
