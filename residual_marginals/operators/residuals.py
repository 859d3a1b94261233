"""Residuals of marginals, and marginals from residuals, on (gamma, cell, value) frames and packed blocks.

In residual coordinates each axis holds its total at index 0 and the differences to slice 0 after it.
One pass over the axes of a marginal then gives all of its residuals in place: the cells
whose non-zero axes are tau hold residual tau.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from residual_marginals.domain import Domain
from residual_marginals.lattice import subsets
from residual_marginals.operators import blocks
from residual_marginals.operators.axisops import AxisProgram
from residual_marginals.shipping import ship


def positions(domain: Domain, gamma: int, tau: int) -> tuple[int, ...]:
    """Places of tau's attributes among those of gamma."""
    if tau & ~gamma:
        raise ValueError("the residual's attributes must be among the marginal's")
    axes = domain.axes(gamma)
    return tuple(axes.index(i) for i in domain.axes(tau))


def residual_of(array: np.ndarray, domain: Domain, gamma: int, tau: int) -> np.ndarray:
    """Residual tau of marginal gamma, as an array over tau's axes only."""
    out = blocks.decompose(array, positions(domain, gamma, tau))
    return out.reshape([n - 1 for n in domain.shape(tau)])


def component_of(residual: np.ndarray, domain: Domain, tau: int, gamma: int) -> np.ndarray:
    """Component of marginal gamma that residual tau stands for."""
    keep, shape = positions(domain, gamma, tau), domain.shape(gamma)
    wide = residual.reshape([n - 1 if k in keep else 1 for k, n in enumerate(shape)])
    return blocks.reconstruct(wide, keep, shape)


def narrow_component(residual: np.ndarray, domain: Domain, tau: int, gamma: int) -> np.ndarray:
    """The component with length 1 on the axes outside tau: smearing is left to broadcasting."""
    return widened(blocks.center_all(residual), domain, tau, gamma)


def widened(centred: np.ndarray, domain: Domain, tau: int, gamma: int) -> np.ndarray:
    """The same from a residual that is centred already, which is one for all marginals."""
    shape = [domain.attributes[i].n if tau >> i & 1 else 1 for i in domain.axes(gamma)]
    return centred.reshape(shape) / domain.size(gamma & ~tau)


def assemble(residuals: dict[int, np.ndarray], domain: Domain, gamma: int) -> np.ndarray:
    """Marginal gamma from all residuals of its subsets (missing ones count as zero), through residual coordinates."""
    coords = np.zeros(domain.shape(gamma))
    for tau in subsets(gamma) if len(residuals) > 1 << gamma.bit_count() else residuals:
        if tau in residuals and tau & gamma == tau:
            keep = positions(domain, gamma, tau)
            at = blocks.support_slices(coords.shape, keep)
            coords[at] = residuals[tau].reshape(coords[at].shape)
    return blocks.from_coords(coords)


def split(array: np.ndarray, domain: Domain, gamma: int) -> dict[int, np.ndarray]:
    """All residuals of a marginal, in one pass."""
    coords = blocks.to_coords(array)
    out = {}
    for tau in subsets(gamma):
        part = coords[blocks.support_slices(coords.shape, positions(domain, gamma, tau))]
        if part.size:
            out[tau] = part.reshape([n - 1 for n in domain.shape(tau)])
    return out


def decompose(cells: DataFrame, domain: Domain, gamma: int, tau: int) -> DataFrame:
    """Residual tau of marginal gamma; ``cells`` is a relation with a column per attribute."""
    positions(domain, gamma, tau)
    return AxisProgram.decompose(domain.names(gamma), domain.shape(gamma), domain.names(tau)).compile_cells(cells)


def reconstruct(residual: DataFrame, domain: Domain, tau: int, gamma: int) -> DataFrame:
    """Component of marginal gamma from the relation of residual tau."""
    positions(domain, gamma, tau)
    return AxisProgram.reconstruct(domain.names(gamma), domain.shape(gamma), domain.names(tau)).compile_cells(residual)


def _stride(domain: Domain, axis: int) -> Column:
    """Cells that one step on an axis spans, in whichever set ``gamma`` is."""
    out = F.lit(1).cast("long")
    for j in range(axis + 1, len(domain)):
        out = out * F.when(F.col("gamma").bitwiseAND(F.lit(1 << j).cast("long")) != 0, F.lit(domain.attributes[j].n)).otherwise(1)
    return out


def _axis(cells: DataFrame, domain: Domain, axis: int, by: tuple[str, ...] = ()) -> tuple[DataFrame, Window]:
    present = F.col("gamma").bitwiseAND(F.lit(1 << axis).cast("long")) != 0
    n = domain.attributes[axis].n
    stride = _stride(domain, axis)
    k = F.when(present, F.floor(F.col("cell") / stride) % n).otherwise(F.lit(0).cast("long"))
    rows = cells.withColumn("_has", present).withColumn("_k", k).withColumn("_line", F.col("cell") - F.col("_k") * stride)
    return rows, Window.partitionBy("gamma", *by, "_line")


def to_residual_coords(cells: DataFrame, domain: Domain, by: tuple[str, ...] = ()) -> DataFrame:
    """(gamma, by, cell, support, value): all residuals of all dense marginals of the frame, in place.

    The columns ``by`` tell tables of one set apart. The frame is dealt by gamma once; every axis pass then works inside that partitioning.
    """
    out = cells.repartition("gamma").withColumn("support", F.lit(0).cast("long"))
    for i in range(len(domain)):
        rows, line = _axis(out, domain, i, by)
        first = F.sum(F.when(F.col("_k") == 0, F.col("value"))).over(line)
        value = F.when(~F.col("_has"), F.col("value")).when(F.col("_k") == 0, F.sum("value").over(line)).otherwise(F.col("value") - first)
        support = F.when(F.col("_k") > 0, F.col("support").bitwiseOR(F.lit(1 << i).cast("long"))).otherwise(F.col("support"))
        out = rows.select("gamma", *by, "cell", support.alias("support"), value.alias("value"))
    return out


def from_residual_coords(coords: DataFrame, domain: Domain) -> DataFrame:
    """Inverse: (gamma, cell, value)."""
    out = coords.select("gamma", "cell", "value").repartition("gamma")
    for i in range(len(domain)):
        n = domain.attributes[i].n
        rows, line = _axis(out, domain, i)
        total = F.sum(F.when(F.col("_k") == 0, F.col("value"))).over(line) / n
        mean = F.coalesce(F.sum(F.when(F.col("_k") > 0, F.col("value"))).over(line), F.lit(0.0)) / n
        own = F.when(F.col("_k") > 0, F.col("value")).otherwise(0.0)
        out = rows.select("gamma", "cell", F.when(F.col("_has"), total + own - mean).otherwise(F.col("value")).alias("value"))
    return out


def decompose_all(cells: DataFrame, domain: Domain, by: tuple[str, ...] = ()) -> DataFrame:
    """(gamma, by, tau, cell, value): every residual, with cells numbered over its own shape."""
    coords = to_residual_coords(cells, domain, by)
    out = F.lit(0).cast("long")
    for i in range(len(domain)):
        n = domain.attributes[i].n
        bit = F.lit(1 << i).cast("long")
        k = F.floor(F.col("cell") / _stride(domain, i)) % n
        out = F.when(F.col("support").bitwiseAND(bit) != 0, out * (n - 1) + k - 1).otherwise(out)
    return coords.select("gamma", *by, F.col("support").alias("tau"), out.alias("cell"), "value")


def pack(cells: DataFrame) -> DataFrame:
    """Dense cells as blocks (gamma, kind, values), one row per marginal."""
    rows = F.array_sort(F.collect_list(F.struct("cell", "value")))
    return cells.groupBy("gamma").agg(rows.alias("r")).select("gamma", F.lit("marginal").alias("kind"), F.col("r.value").alias("values"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("gamma", F.posexplode("values").alias("cell", "value")).withColumn("cell", F.col("cell").cast("long"))


def map_blocks(packed: DataFrame, domain: Domain, kernel, kind: str) -> DataFrame:
    """Apply an array kernel to every packed block, without a shuffle."""
    ship(packed.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            values = [kernel(np.asarray(v).reshape(domain.shape(g))).ravel() for g, v in zip(batch["gamma"].tolist(), batch["values"])]
            yield pd.DataFrame({"gamma": batch["gamma"], "kind": kind, "values": values})

    return packed.mapInPandas(run, "gamma long, kind string, values array<double>")


def cheapest_source(tau: int, sources: list[int], domain: Domain) -> int:
    """The smallest marginal that a residual can be read from."""
    fit = [s for s in sources if s & tau == tau]
    if not fit:
        raise ValueError("no source holds the residual's attributes")
    return min(fit, key=lambda s: (domain.size(s), s))


def cells_of(domain: Domain, tau: int) -> int:
    return math.prod(n - 1 for n in domain.shape(tau))
