"""In-axis operations on one marginal as a relation: a column per attribute, and ``value``.

An ``AxisProgram`` is a list of steps; it can be compiled to DataFrame operators, to array
kernels, or to per-axis factors.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from residual_marginals.operators import blocks


def axis_sum(cells: DataFrame, axes: list[str], axis: str) -> DataFrame:
    """Add up along an axis, which goes away."""
    return cells.groupBy(*[a for a in axes if a != axis]).agg(F.sum("value").alias("value"))


def axis_sub(cells: DataFrame, axes: list[str], axis: str) -> DataFrame:
    """Take slice 0 from the others and drop it; code k becomes k - 1."""
    others = [a for a in axes if a != axis]
    first = cells.where(F.col(axis) == 0).select(*others, F.col("value").alias("_first"))
    rest = cells.where(F.col(axis) > 0)
    joined = rest.join(first, others) if others else rest.crossJoin(F.broadcast(first))
    return joined.select(*[(F.col(a) - 1).alias(a) if a == axis else F.col(a) for a in axes], (F.col("value") - F.col("_first")).alias("value"))


def axis_center(cells: DataFrame, axes: list[str], axis: str, n: int) -> DataFrame:
    """Put a zero slice in front and take the axis mean from all; ``n`` is the new length."""
    others = [a for a in axes if a != axis]
    mean = cells.groupBy(*others).agg((F.sum("value") / n).alias("_mean"))
    joined = cells.join(mean, others) if others else cells.crossJoin(F.broadcast(mean))
    rest = joined.select(*[(F.col(a) + 1).alias(a) if a == axis else F.col(a) for a in axes], (F.col("value") - F.col("_mean")).alias("value"))
    front = mean.select(*[F.lit(0).alias(a) if a == axis else F.col(a) for a in axes], (-F.col("_mean")).alias("value"))
    return rest.unionByName(front)


def axis_smear(cells: DataFrame, axes: list[str], axis: str, k: int) -> DataFrame:
    """Add an axis of length k over which the value is spread evenly."""
    return cells.select(*[a for a in axes if a != axis], F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias(axis), (F.col("value") / k).alias("value"))


def component_direct(cells: DataFrame, axes: list[str], keep: list[str]) -> DataFrame:
    """Component over the kept axes by window means, axis by axis; every axis stays."""
    for axis in axes:
        mean = F.avg("value").over(Window.partitionBy(*[a for a in axes if a != axis] or [F.lit(0)]))
        cells = cells.withColumn("value", F.col("value") - mean if axis in keep else mean)
    return cells.select(*axes, "value")


@dataclass(frozen=True)
class Step:
    """``kind`` is sum, sub, center or smear; ``n`` the length after center or smear."""

    kind: str
    axis: str
    n: int = 0


class AxisProgram:
    """Steps on named axes with known lengths."""

    def __init__(self, steps: list[Step], axes: list[str], shape: tuple[int, ...]):
        self.steps, self.axes, self.shape = list(steps), list(axes), tuple(shape)

    @classmethod
    def decompose(cls, axes: list[str], shape: tuple[int, ...], keep: list[str]) -> AxisProgram:
        return cls([*(Step("sum", a) for a in axes if a not in keep), *(Step("sub", a) for a in axes if a in keep)], axes, shape)

    @classmethod
    def reconstruct(cls, axes: list[str], shape: tuple[int, ...], keep: list[str]) -> AxisProgram:
        size = dict(zip(axes, shape))
        return cls([*(Step("center", a, size[a]) for a in axes if a in keep), *(Step("smear", a, size[a]) for a in axes if a not in keep)], axes, shape)

    def simplify(self) -> AxisProgram:
        """Steps on different axes commute: shrinking steps first (sums, then differences), growing ones last; smearing to length 1 goes."""
        rank = {"sum": 0, "sub": 1, "center": 2, "smear": 3}
        by_axis: dict[str, int] = {}
        keyed = []
        for k, s in enumerate(self.steps):
            # the order of steps on one axis stays
            place = max(rank[s.kind], by_axis.get(s.axis, 0))
            by_axis[s.axis] = place
            keyed.append((place, k, s))
        steps = [s for _, _, s in sorted(keyed, key=lambda x: x[:2]) if not (s.kind == "smear" and s.n == 1)]
        return AxisProgram(steps, self.axes, self.shape)

    def compile_cells(self, cells: DataFrame) -> DataFrame:
        """As DataFrame operators; axes summed away are columns no more, smeared ones come back."""
        live = [a for a in self.axes if a in cells.columns]
        for s in self.steps:
            if s.kind == "sum":
                cells = axis_sum(cells, live, s.axis)
                live = [a for a in live if a != s.axis]
            elif s.kind == "sub":
                cells = axis_sub(cells, live, s.axis)
            elif s.kind == "center":
                cells = axis_center(cells, live, s.axis, s.n)
            else:
                cells = axis_smear(cells, live, s.axis, s.n)
                live = [*[a for a in live if a != s.axis], s.axis]
        return cells.select(*[a for a in self.axes if a in live], "value")

    def compile_block(self, block: np.ndarray) -> np.ndarray:
        """As array kernels on a block with one dimension per axis."""
        for s in self.steps:
            axis = self.axes.index(s.axis)
            if s.kind == "smear":
                block = blocks.axis_smear(block, axis, s.n)
            else:
                block = {"sum": blocks.axis_sum, "sub": blocks.axis_sub, "center": blocks.axis_center}[s.kind](block, axis)
        return block

    def compile_kron(self) -> list[np.ndarray]:
        """As one factor per axis."""
        parts = [np.eye(n) for n in self._start()]
        for s in self.steps:
            axis = self.axes.index(s.axis)
            n = parts[axis].shape[0]
            m = {"sum": lambda: np.ones((1, n)), "sub": lambda: blocks.difference_matrix(n), "center": lambda: blocks.center_matrix(s.n), "smear": lambda: np.full((s.n, 1), 1 / s.n)}[s.kind]()
            parts[axis] = m @ parts[axis]
        return parts

    def _start(self) -> list[int]:
        kinds = {s.axis: s.kind for s in reversed(self.steps)}
        return [n - 1 if kinds.get(a) == "center" else 1 if kinds.get(a) == "smear" else n for a, n in zip(self.axes, self.shape)]

    def op_count(self) -> int:
        """Cells read by all steps."""
        size = dict(zip(self.axes, self._start()))
        total = 0
        for s in self.steps:
            cells = 1
            for n in size.values():
                cells *= n
            total += cells
            size[s.axis] = {"sum": 1, "sub": size[s.axis] - 1}.get(s.kind, s.n)
        return total


def kron_cells(cells: DataFrame, axes: list[str], parts: dict[str, np.ndarray]) -> DataFrame:
    """Relational form of the explicit baseline: per axis, join the factor's non-zero entries and sum."""
    spark = cells.sparkSession
    for axis in axes:
        m = parts[axis]
        entries = [(int(j), int(i), float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1]) if m[i, j]]
        factor = spark.createDataFrame(entries, f"{axis} int, _to int, _w double")
        joined = cells.join(F.broadcast(factor), axis).drop(axis).withColumnRenamed("_to", axis)
        cells = joined.groupBy(*axes).agg(F.sum(F.col("value") * F.col("_w")).alias("value"))
    return cells.select(*axes, "value")
