"""Attribute sets as bit masks: subsets, closures, workloads."""

from __future__ import annotations

from collections.abc import Iterable
from functools import lru_cache, reduce
from itertools import combinations
from operator import or_

from pyspark.sql import DataFrame, SparkSession

from residual_marginals.domain import Domain


def subsets(mask: int) -> list[int]:
    """All subsets of a set, the empty one first, the set itself last."""
    out, sub = [], mask
    while True:
        out.append(sub)
        if not sub:
            return out[::-1]
        sub = (sub - 1) & mask


def closure(masks: Iterable[int]) -> list[int]:
    """All subsets of the sets, by size then value."""
    return sorted({s for m in masks for s in subsets(m)}, key=lambda m: (m.bit_count(), m))


def maximal(masks: Iterable[int]) -> list[int]:
    """The sets that are in no other, by falling size."""
    out: list[int] = []
    by_bit: dict[int, list[int]] = {}
    for m in sorted(set(masks), key=lambda m: (-m.bit_count(), m)):
        near = by_bit.get(m & -m, ()) if m else out
        if not any(m & o == m for o in near):
            out.append(m)
            for i in range(m.bit_length()):
                if m >> i & 1:
                    by_bit.setdefault(1 << i, []).append(m)
    return out


class Workload:
    """Sets of attributes whose marginals are wanted, with weights."""

    def __init__(self, sets: Iterable[int], weights: Iterable[float] | None = None):
        self.sets = list(sets)
        self.weights = list(weights) if weights is not None else [1.0] * len(self.sets)
        if len(self.sets) != len(self.weights):
            raise ValueError("one weight per set")

    @classmethod
    def all_kway(cls, domain: Domain, k: int, weights: Iterable[float] | None = None) -> Workload:
        if k > len(domain):
            raise ValueError("more attributes asked for than there are")
        return cls([sum(1 << i for i in c) for c in combinations(range(len(domain)), k)], weights)

    @classmethod
    def from_sets(cls, domain: Domain, names: Iterable[Iterable[str]]) -> Workload:
        return cls([domain.mask(n) for n in names])

    @classmethod
    def with_target(cls, domain: Domain, target: str, k: int) -> Workload:
        """All k-way sets that hold one attribute."""
        bit = 1 << domain.index[target]
        return cls([m for m in cls.all_kway(domain, k).sets if m & bit])

    def weighted(self, weights: dict[int, float]) -> Workload:
        return Workload(self.sets, [weights.get(s, 1.0) for s in self.sets])

    def closure(self) -> list[int]:
        return closure(self.sets)

    def maximal(self) -> list[int]:
        top = set(maximal(self.sets))
        return [s for s in self.sets if s in top]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(list(zip(self.sets, map(float, self.weights))), "gamma long, weight double")


def cover_plan(sets: Iterable[int], domain: Domain, max_cells: int = 1 << 20) -> list[int]:
    """Fewer, larger tables that cover the sets: each joins the table that it lets grow least, within ``max_cells``."""
    tables: list[list[int]] = []  # mask, cells
    size = lru_cache(maxsize=None)(domain.size)
    for s in sorted(set(sets), key=lambda m: (-domain.size(m), m)):
        best, least = None, None
        for t in tables:
            more = s & ~t[0]
            if not more:
                best, least = t, 0
                break
            grown = t[1] * size(more)
            if grown <= max_cells and (least is None or grown - t[1] < least):
                best, least = t, grown - t[1]
        if best is None:
            tables.append([s, domain.size(s)])
        elif least:
            best[0], best[1] = best[0] | s, best[1] + least
    return sorted({t[0] for t in tables})


def block_cover(sets: Iterable[int], domain: Domain, max_cells: int = 1 << 20) -> list[int]:
    """The same for very many sets: attributes are dealt to blocks, and a set's table is the union of its attributes' blocks.

    A block has at most the k-th root of ``max_cells`` cells (or one attribute), for sets of at most k attributes.
    """
    sets = list(sets)
    room = max_cells ** (1 / max(1, max((s.bit_count() for s in sets), default=1)))
    blocks: list[int] = []
    for i in sorted(range(len(domain)), key=lambda i: -domain.attributes[i].n):
        home = next((k for k, b in enumerate(blocks) if domain.size(b) * domain.attributes[i].n <= room), None)
        if home is None:
            blocks.append(1 << i)
        else:
            blocks[home] |= 1 << i
    block_of = {i: b for b in blocks for i in range(len(domain)) if b >> i & 1}
    unions = {s: reduce(or_, (block_of[i] for i in domain.axes(s)), 0) for s in sets}
    fits = {u: domain.size(u) <= max_cells for u in set(unions.values())}
    return sorted(set(maximal(u if fits[u] else s for s, u in unions.items())))


def touched(alpha: int, sets: Iterable[int]) -> int:
    """Marginals that a change of residual ``alpha`` reaches."""
    return sum(s & alpha == alpha for s in sets)
