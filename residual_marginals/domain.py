"""Declared domains: which attributes there are, how raw columns become codes and back."""

from __future__ import annotations

import math
import warnings
from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Attribute:
    """A categorical attribute; ``coder`` is a SQL expression for its code 0..n-1."""

    name: str
    n: int
    coder: str
    labels: tuple[str, ...] | None = None

    def __post_init__(self) -> None:
        if self.n < 1:
            raise ValueError(f"attribute {self.name}: n must be at least 1")


class Domain:
    """Ordered attributes. Attribute sets are integers: bit i stands for attribute i (any number of attributes)."""

    def __init__(self, attributes: Sequence[Attribute]):
        self.attributes = tuple(attributes)
        self.index = {a.name: i for i, a in enumerate(self.attributes)}
        if len(self.index) < len(self.attributes):
            raise ValueError("duplicate attribute names")
        self._axes: dict[int, tuple[int, ...]] = {}
        self._shapes: dict[int, tuple[int, ...]] = {}

    def __getstate__(self) -> dict:
        # what was looked up does not travel to the tasks
        return {**self.__dict__, "_axes": {}, "_shapes": {}}

    def __len__(self) -> int:
        return len(self.attributes)

    def mask(self, names: Iterable[str]) -> int:
        return sum(1 << self.index[n] for n in set(names))

    def axes(self, mask: int) -> tuple[int, ...]:
        if mask not in self._axes:
            self._axes[mask] = tuple(i for i in range(len(self.attributes)) if mask >> i & 1)
        return self._axes[mask]

    def names(self, mask: int) -> list[str]:
        return [self.attributes[i].name for i in self.axes(mask)]

    def shape(self, mask: int) -> tuple[int, ...]:
        if mask not in self._shapes:
            self._shapes[mask] = tuple(self.attributes[i].n for i in self.axes(mask))
        return self._shapes[mask]

    def size(self, mask: int) -> int:
        return math.prod(self.shape(mask))

    def cell(self, mask: int) -> Column:
        """Row-major cell number of a coded row."""
        out = F.lit(0).cast("long")
        for i in self.axes(mask):
            out = out * F.lit(self.attributes[i].n) + F.col(self.attributes[i].name).cast("long")
        return out

    def to_df(self, spark: SparkSession) -> DataFrame:
        rows = [(a.name, i, a.n, list(a.labels) if a.labels else None) for i, a in enumerate(self.attributes)]
        return spark.createDataFrame(rows, "attr string, axis int, n int, labels array<string>")


def encode(df: DataFrame, domain: Domain, on_unknown: str = "clamp") -> DataFrame:
    """One int column per attribute. Codes outside 0..n-1 and nulls: ``clamp`` to the nearest code (null to 0), ``other`` to n-1, ``fail``."""
    columns = []
    for a in domain.attributes:
        code = F.expr(a.coder).cast("int")
        if on_unknown == "clamp":
            code = F.least(F.greatest(F.coalesce(code, F.lit(0)), F.lit(0)), F.lit(a.n - 1))
        elif on_unknown == "other":
            code = F.when(code.between(0, a.n - 1), code).otherwise(a.n - 1)
        elif on_unknown == "fail":
            code = F.when(code.between(0, a.n - 1), code).otherwise(F.raise_error(F.lit(f"{a.name}: value outside the domain")).cast("int"))
        else:
            raise ValueError("on_unknown must be clamp, other or fail")
        columns.append(code.alias(a.name))
    return df.select(*columns)


def decode(cells: DataFrame, domain: Domain, gamma: int) -> DataFrame:
    """Adds one code column per attribute of ``gamma``, and labels where the domain declares them."""
    rest = F.col("cell")
    for i in reversed(domain.axes(gamma)):
        a = domain.attributes[i]
        code = (rest % a.n).cast("int")
        cells = cells.withColumn(a.name, code)
        if a.labels:
            cells = cells.withColumn(f"{a.name}_label", F.element_at(F.array(*map(F.lit, a.labels)), code + 1))
        rest = F.floor(rest / a.n)
    return cells


def infer_domain(df: DataFrame, columns: Sequence[str], most: int = 10_000) -> Domain:
    """A domain read off the data. Not private: the categories themselves are taken from the rows.

    A column with more than ``most`` values is refused: it needs a coder that groups them.
    """
    warnings.warn("a domain inferred from the data is not covered by the privacy guarantee", stacklevel=2)
    out = []
    for c in columns:
        values = sorted((r[0] for r in df.select(F.col(c).cast("string")).distinct().limit(most + 1).collect()), key=lambda v: (v is not None, v or ""))
        if len(values) > most:
            raise ValueError(f"{c} has more than {most} values")
        quoted = [v.replace("'", "''") for v in values if v is not None]
        cases = " ".join(f"WHEN '{v}' THEN {k}" for k, v in enumerate(quoted))
        out.append(Attribute(c, max(1, len(quoted)), f"CASE CAST({c} AS STRING) {cases} END" if cases else "0", tuple(quoted)))
    return Domain(out)
