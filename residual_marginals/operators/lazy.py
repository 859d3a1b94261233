"""Lazy updates: after a new measurement only marginals that contain the residual's attributes change, by one component."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from residual_marginals.domain import Domain
from residual_marginals.operators import residuals
from residual_marginals.operators.reconstruct import reconstruct_all
from residual_marginals.shipping import ship

#: Cells of a round's changes that are broadcast at most; larger rounds go through a join.
BROADCAST_CELLS = 1 << 22


def lazy_round(packed: DataFrame, domain: Domain, deltas: dict[int, np.ndarray]) -> DataFrame:
    """Add all of a round's residual changes to the packed blocks that contain them; other blocks pass through untouched.

    By linearity the changes of one round are merged in residual coordinates first, so a block is transformed once. One narrow pass
    over the blocks; the changes are a broadcast of bounded size.
    """
    if sum(d.size for d in deltas.values()) > BROADCAST_CELLS:
        raise ValueError("the round's changes are too large to broadcast; use lazy_cells")
    ship(packed.sparkSession)
    told = packed.sparkSession.sparkContext.broadcast(deltas)

    def add(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        changes = told.value
        for batch in batches:
            values = []
            for gamma, v in zip(batch["gamma"].tolist(), batch["values"]):
                own = {a: d for a, d in changes.items() if gamma & a == a}
                values.append(np.asarray(v) + residuals.assemble(own, domain, gamma).ravel() if own else v)
            yield batch.assign(values=values)

    return packed.mapInPandas(add, packed.schema)


def lazy_cells(cells: DataFrame, domain: Domain, deltas: DataFrame) -> DataFrame:
    """The same on (gamma, cell, value) with changes (tau, cell, value) of any size, by joins."""
    masks = [r["gamma"] for r in cells.select("gamma").distinct().collect()]
    taus = [r["tau"] for r in deltas.select("tau").distinct().collect()]
    reached = [g for g in masks if any(g & t == t for t in taus)]
    if not reached:
        return cells
    change = reconstruct_all(deltas.withColumn("precision", F.lit(1.0)), domain, reached).withColumnRenamed("value", "_change")
    return cells.join(change, ["gamma", "cell"], "left").select("gamma", "cell", (F.col("value") + F.coalesce("_change", F.lit(0.0))).alias("value"))


def full_rebuild(estimates: DataFrame, domain: Domain, masks: list[int]) -> DataFrame:
    """Baseline: every marginal anew from the estimates."""
    return reconstruct_all(estimates, domain, masks)
