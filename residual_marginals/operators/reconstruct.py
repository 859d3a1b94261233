"""All answers from noisy residuals: inverse-variance averages per residual, then one inverse transform per marginal."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from residual_marginals.domain import Domain
from residual_marginals.lattice import subsets
from residual_marginals.operators import residuals
from residual_marginals.operators.measure import marginal_to_residuals


def consolidate(measurements: DataFrame) -> DataFrame:
    """(tau, precision, cell, value): the average of all measurements of each residual, weighted by 1 / sigma2."""
    weight = 1 / F.col("sigma2")
    return measurements.groupBy("tau", "cell").agg(F.sum(weight).alias("precision"), (F.sum(F.col("value") * weight) / F.sum(weight)).alias("value")).select("tau", "precision", "cell", "value")


def with_unmeasured(estimates: DataFrame, domain: Domain, taus: Iterable[int]) -> DataFrame:
    """Estimates for every residual of ``taus``; those never measured are zero with precision zero."""
    sizes = estimates.sparkSession.createDataFrame([(t, residuals.cells_of(domain, t)) for t in taus], "tau long, n long").where("n > 0")
    wanted = sizes.select("tau", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("cell"))
    return wanted.join(estimates, ["tau", "cell"], "left").select("tau", F.coalesce("precision", F.lit(0.0)).alias("precision"), "cell", F.coalesce("value", F.lit(0.0)).alias("value"))


def reconstruct_all(estimates: DataFrame, domain: Domain, masks: Iterable[int]) -> DataFrame:
    """(gamma, cell, value) for all masks: each marginal's residual coordinates are joined from the estimates and inverted."""
    spark = estimates.sparkSession
    masks = list(masks)
    parts = spark.createDataFrame([(g, t) for g in masks for t in subsets(g)], "gamma long, tau long")
    codes = F.col("cell")
    cell, stride = F.lit(0).cast("long"), F.lit(1).cast("long")
    # the residual's cell number is read from its last axis on, and written with the marginal's strides
    for i in reversed(range(len(domain))):
        n = domain.attributes[i].n
        bit = F.lit(1 << i).cast("long")
        in_tau, in_gamma = F.col("tau").bitwiseAND(bit) != 0, F.col("gamma").bitwiseAND(bit) != 0
        if n > 1:
            cell = F.when(in_tau, cell + (codes % (n - 1) + 1) * stride).otherwise(cell)
            codes = F.when(in_tau, F.floor(codes / (n - 1))).otherwise(codes)
        stride = F.when(in_gamma, stride * n).otherwise(stride)
    placed = estimates.join(F.broadcast(parts), "tau").select("gamma", cell.cast("long").alias("cell"), "value")
    sizes = spark.createDataFrame([(g, domain.size(g)) for g in masks], "gamma long, n long")
    wanted = sizes.select("gamma", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("cell"))
    coords = wanted.join(placed, ["gamma", "cell"], "left").withColumn("value", F.coalesce("value", F.lit(0.0)))
    return residuals.from_residual_coords(coords, domain)


def reconstruct_from(domain: Domain, masks: Iterable[int], marginals: DataFrame | None = None, measured_residuals: DataFrame | None = None) -> DataFrame:
    """Answers from noisy marginals, noisy residuals, or both."""
    parts = []
    if marginals is not None:
        parts.append(marginal_to_residuals(marginals, domain).select("tau", "sigma2", "cell", "value"))
    if measured_residuals is not None:
        parts.append(measured_residuals.select("tau", "sigma2", "cell", "value"))
    if not parts:
        raise ValueError("nothing was measured")
    both = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    return reconstruct_all(consolidate(both), domain, masks)


def consistency_gap(marginals: DataFrame, domain: Domain, gamma: int, other: int) -> float:
    """Largest difference between two estimated marginals on the attributes that they share."""
    from residual_marginals.operators.tabulate import roll_up

    shared = gamma & other
    a, b = (roll_up(marginals, domain, m, [shared]).select("cell", F.col("value").alias(c)) for m, c in ((gamma, "a"), (other, "b")))
    return a.join(b, "cell", "full").agg(F.max(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0))))).first()[0]


def update_estimate(estimates: DataFrame, measured: DataFrame) -> DataFrame:
    """Estimates after further measurements (tau, sigma2, cell, value) of residuals."""
    old = estimates.where("precision > 0").select("tau", (1 / F.col("precision")).alias("sigma2"), "cell", "value")
    return consolidate(old.unionByName(measured.select("tau", "sigma2", "cell", "value")))


def postprocess(cells: DataFrame, clip: bool = True, renormalise: bool = True) -> DataFrame:
    """Non-negative cells with each marginal's total kept. Breaks the agreement between marginals, so off by default elsewhere."""
    out = cells.withColumn("_new", F.greatest("value", F.lit(0.0)) if clip else F.col("value"))
    if renormalise:
        totals = out.groupBy("gamma").agg(F.sum("value").alias("_was"), F.sum("_new").alias("_is"))
        out = out.join(totals, "gamma").withColumn("_new", F.when(F.col("_is") > 0, F.col("_new") * F.greatest("_was", F.lit(0.0)) / F.col("_is")).otherwise(F.col("_new")))
    return out.select("gamma", "cell", F.col("_new").alias("value"))
