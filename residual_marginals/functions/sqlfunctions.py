"""SQL surface: subsets, transforms of packed blocks, privacy coefficients and conversions."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType

from residual_marginals.lattice import closure, subsets
from residual_marginals.operators import blocks
from residual_marginals.shipping import ship


@udtf(returnType="tau bigint")
class Subsets:
    """All subsets of a mask."""

    def eval(self, mask: int) -> Iterator[tuple[int]]:
        for s in subsets(mask):
            yield (s,)


@udtf(returnType="gamma bigint")
class Closure:
    """All subsets of an array of masks, each once."""

    def eval(self, masks: list[int]) -> Iterator[tuple[int]]:
        for s in closure(masks):
            yield (s,)


@udtf(returnType="values array<double>")
class Decompose:
    """Residual over the axes ``keep`` of a packed row-major marginal."""

    def eval(self, values: list[float], shape: list[int], keep: list[int]) -> Iterator[tuple[list[float]]]:
        yield (blocks.decompose(np.array(values).reshape(shape), tuple(keep)).ravel().tolist(),)


@udtf(returnType="values array<double>")
class Reconstruct:
    """Component of shape ``shape`` from a packed residual over the axes ``keep``."""

    def eval(self, values: list[float], shape: list[int], keep: list[int]) -> Iterator[tuple[list[float]]]:
        wide = np.array(values).reshape([n - 1 if k in keep else 1 for k, n in enumerate(shape)])
        yield (blocks.reconstruct(wide, tuple(keep), tuple(shape)).ravel().tolist(),)


@pandas_udf(LongType())
def marginal_cell(codes: pd.Series, sizes: pd.Series) -> pd.Series:
    """Row-major cell of arrays of codes."""
    return pd.Series([int(np.ravel_multi_index([int(c) for c in code], [int(n) for n in size])) for code, size in zip(codes, sizes)])


@pandas_udf(DoubleType())
def block_l1(a: pd.Series, b: pd.Series) -> float:
    """Summed absolute difference of columns, as a grouped aggregate."""
    return float((a - b).abs().sum())


def register(spark: SparkSession) -> None:
    """Make all functions known to SQL under ``rm_`` names."""
    ship(spark)
    for name, function in (("rm_subsets", Subsets), ("rm_closure", Closure), ("rm_decompose", Decompose), ("rm_reconstruct", Reconstruct)):
        spark.udtf.register(name, function)
    spark.udf.register("rm_cell", marginal_cell)
    spark.udf.register("rm_block_l1", block_l1)
    # the simple conversion and the coefficients stay inside the JVM
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rm_rho_to_eps(rho DOUBLE, delta DOUBLE) RETURNS DOUBLE RETURN rho + 2 * sqrt(rho * ln(1 / delta))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rm_privacy_coef(shape ARRAY<INT>) RETURNS DOUBLE RETURN aggregate(shape, CAST(1 AS DOUBLE), (p, n) -> p * (n - 1) / n)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rm_error_coef(kept ARRAY<INT>, rest ARRAY<INT>) RETURNS DOUBLE RETURN aggregate(kept, CAST(1 AS DOUBLE), (p, n) -> p * (n - 1) / n) * aggregate(rest, CAST(1 AS DOUBLE), (p, n) -> p / n / n)")


def rho_to_eps_column(rho, delta: float):
    """The simple conversion as a column expression."""
    return rho + 2 * F.sqrt(rho * math.log(1 / delta))
