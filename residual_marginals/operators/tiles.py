"""One marginal too large for a block: tiles over its first axes, transformed tile by tile.

A frame of tiles is (tile, values): ``tile`` holds the codes of the first ``lead`` axes, ``values`` the row-major cells of the others. Steps on the
other axes are a narrow pass over the tiles; a step on a leading axis gathers the tiles of one line, as many as the axis is long.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.operators import blocks
from residual_marginals.shipping import ship

SCHEMA = "tile array<int>, values array<double>"


def from_cells(cells: DataFrame, shape: tuple[int, ...], lead: int = 2) -> DataFrame:
    """Tiles of dense (cell, value)."""
    rest = int(np.prod(shape[lead:], dtype=np.int64))
    code, codes = F.floor(F.col("cell") / rest), []
    for n in reversed(shape[:lead]):
        codes.append((code % n).cast("int"))
        code = F.floor(code / n)
    ordered = F.array_sort(F.collect_list(F.struct((F.col("cell") % rest).alias("c"), F.col("value").cast("double").alias("v"))))
    rows = cells.select(F.array(*reversed(codes)).alias("tile"), "cell", "value")
    return rows.groupBy("tile").agg(ordered.alias("r")).select("tile", F.col("r.v").alias("values"))


def generated(spark: SparkSession, shape: tuple[int, ...], value: Callable[[Column], Column], lead: int = 2) -> DataFrame:
    """Tiles whose cells are an expression of their row-major number; nothing larger than a tile is built."""
    rest = int(np.prod(shape[lead:], dtype=np.int64))
    tiles = spark.range(int(np.prod(shape[:lead], dtype=np.int64)))
    code, codes = F.col("id"), []
    for n in reversed(shape[:lead]):
        codes.append((code % n).cast("int"))
        code = F.floor(code / n)
    cells = F.transform(F.sequence(F.col("id") * rest, (F.col("id") + 1) * rest - 1), lambda cell: value(cell).cast("double"))
    return tiles.select(F.array(*reversed(codes)).alias("tile"), cells.alias("values"))


def to_cells(tiles: DataFrame, shape: tuple[int, ...], lead: int = 2) -> DataFrame:
    """(cell, value) of tiles whose marginal or residual has ``shape``."""
    rest = int(np.prod(shape[lead:], dtype=np.int64))
    number = F.lit(0).cast("long")
    for k, n in enumerate(shape[:lead]):
        number = number * n + F.col("tile")[k]
    return tiles.select(number.alias("t"), F.posexplode("values").alias("at", "value")).select((F.col("t") * rest + F.col("at")).alias("cell"), "value")


def _inside(tiles: DataFrame, kernel) -> DataFrame:
    ship(tiles.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for k in range(len(batch)):
                one = batch.iloc[k : k + 1]
                yield one.assign(values=[kernel(np.asarray(one["values"].iloc[0])).ravel()])

    return tiles.mapInPandas(run, SCHEMA)


def _across(tiles: DataFrame, axis: int, kernel) -> DataFrame:
    """A step on a leading axis: ``kernel`` gets the stacked tiles of a line."""
    lead = F.transform("tile", lambda c, k: F.when(k == axis, F.lit(0)).otherwise(c))

    def run(line: pd.DataFrame) -> pd.DataFrame:
        line = line.sort_values("at")
        out = kernel(np.stack([np.asarray(v) for v in line["values"]]))
        tile = list(line["tile"].iloc[0])
        return pd.DataFrame({"tile": [[*tile[:axis], k, *tile[axis + 1 :]] for k in range(len(out))], "values": list(out)})

    keyed = tiles.select("tile", "values", F.col("tile")[axis].alias("at"), lead.alias("line"))
    return keyed.groupBy("line").applyInPandas(run, SCHEMA)


def decompose(tiles: DataFrame, shape: tuple[int, ...], keep: tuple[int, ...], lead: int = 2) -> DataFrame:
    """Residual over the kept axes; summed axes stay with length 1. Sums come first, so later steps see fewer cells."""
    inner = tuple(k - lead for k in keep if k >= lead)
    out = _inside(tiles, lambda v: blocks.decompose(v.reshape(shape[lead:]), inner))
    for axis in sorted(range(lead), key=lambda a: a in keep):
        out = _across(out, axis, lambda a, own=axis in keep: blocks.axis_sub(a, 0) if own else blocks.axis_sum(a, 0))
    return out


def reconstruct(tiles: DataFrame, shape: tuple[int, ...], keep: tuple[int, ...], lead: int = 2) -> DataFrame:
    """Component of a marginal of ``shape`` from tiles of the residual over the kept axes."""
    inner = tuple(k - lead for k in keep if k >= lead)
    small = [n - 1 if k + lead in keep else 1 for k, n in enumerate(shape[lead:])]
    out = tiles
    for axis in sorted(range(lead), key=lambda a: a not in keep):
        out = _across(out, axis, lambda a, own=axis in keep, n=shape[axis]: blocks.axis_center(a, 0) if own else blocks.axis_smear(a, 0, n))
    return _inside(out, lambda v: blocks.reconstruct(v.reshape(small), inner, shape[lead:]))
