"""Exact marginals of coded rows: one scan of the data for all sets, small partial counts, dense tables.

Frames of many marginals are (gamma, cell, value): the attribute set, the row-major cell and the count.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from residual_marginals.domain import Domain
from residual_marginals.lattice import block_cover, cover_plan, maximal
from residual_marginals.shipping import ship
from residual_marginals.sources.io import cut

#: Dense partial counts one task may hold, in cells.
TASK_CELLS = 1 << 23
#: Sets up to which tables that cover them are searched one by one.
GREEDY_SETS = 2000
#: Rows that a task counts at once.
HELD_ROWS = 1 << 17


def tabulate_one(coded: DataFrame, names: list[str]) -> DataFrame:
    """One marginal as a relation: a column per attribute and ``value`` (bigint); absent cells are absent."""
    return coded.groupBy(*names).agg(F.count(F.lit(1)).alias("value"))


def grouping_sets(coded: DataFrame, domain: Domain, masks: Iterable[int]) -> DataFrame:
    """Many marginals by GROUPING SETS: one Expand, partial counts, one exchange."""
    masks = list(masks)
    names = [a.name for a in domain.attributes]
    used = [n for n in names if any(m & domain.mask([n]) for m in masks)]
    sets = ", ".join("(" + ", ".join(domain.names(m)) + ")" for m in masks)
    coded.createOrReplaceTempView("_coded_rows")
    flags = ", ".join(f"grouping({n}) AS _g_{n}" for n in used)
    grouped = coded.sparkSession.sql(f"SELECT {', '.join(used)}, {flags}, count(*) AS value FROM _coded_rows GROUP BY GROUPING SETS ({sets})")
    gamma = sum((F.lit(1 << domain.index[n]).cast("long") * (1 - F.col(f"_g_{n}")) for n in used), F.lit(0).cast("long"))
    cell = F.lit(0).cast("long")
    for n in used:
        size = domain.attributes[domain.index[n]].n
        cell = F.when(F.col(f"_g_{n}") == 1, cell).otherwise(cell * size + F.col(n))
    return grouped.select(gamma.alias("gamma"), cell.alias("cell"), F.col("value").cast("long"))


def explode_sets(coded: DataFrame, domain: Domain, masks: Iterable[int]) -> DataFrame:
    """Many marginals by emitting each row's (gamma, cell) pairs."""
    pairs = F.array(*[F.struct(F.lit(m).cast("long").alias("gamma"), domain.cell(m).alias("cell")) for m in masks])
    return coded.select(F.explode(pairs).alias("p")).groupBy("p.gamma", "p.cell").agg(F.count(F.lit(1)).alias("value"))


class Partial:
    """A task's partial counts: dense tables for the sets that fit into ``TASK_CELLS`` together, sums of what was held for the others."""

    def __init__(self, sizes: dict[int, int], room: int, number: dict[int, int]):
        self.number = number
        self.dense: dict[int, np.ndarray] = {}
        self.rest: dict[int, list] = {}
        for m in sorted(sizes, key=lambda m: (sizes[m], m)):
            room -= sizes[m]
            if room >= 0:
                self.dense[m] = np.zeros(sizes[m], np.int64)
            else:
                self.rest[m] = []

    def add(self, m: int, cells: np.ndarray, weights: np.ndarray | None = None) -> None:
        if m in self.rest:
            self.rest[m].append((cells, np.ones(len(cells), np.int64) if weights is None else weights))
        elif len(self.dense[m]) <= 4 * len(cells):
            # counts of a part stay below 2 ** 53, where sums of doubles are exact
            self.dense[m] += np.bincount(cells, weights, minlength=len(self.dense[m])).astype(np.int64)
        else:
            np.add.at(self.dense[m], cells, 1 if weights is None else weights)

    def spill(self) -> Iterator[pa.RecordBatch]:
        """The sets without a table, summed over what is held."""
        for m, parts in self.rest.items():
            if parts:
                cells, where = np.unique(np.concatenate([c for c, _ in parts]), return_inverse=True)
                sums = np.zeros(len(cells), np.int64)
                np.add.at(sums, where, np.concatenate([w for _, w in parts]))
                self.rest[m] = []
                yield self._batch(m, cells, sums)

    def finish(self) -> Iterator[pa.RecordBatch]:
        yield from self.spill()
        for m, counts in self.dense.items():
            at = np.nonzero(counts)[0]
            yield self._batch(m, at, counts[at])

    def _batch(self, m: int, cells: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(cells), self.number[m], np.int64)), pa.array(cells.astype(np.int64)), pa.array(counts)], names=["gamma", "cell", "value"])


def numbers_of(masks: Iterable[int]) -> dict[int, int]:
    """What stands for each set in the column ``gamma``: the mask where all fit into a long, else its place among the sorted masks."""
    masks = sorted(set(masks))  # the largest last
    return {m: m if masks[-1] < 1 << 62 else k for k, m in enumerate(masks)}


def bincount(coded: DataFrame, domain: Domain, masks: Iterable[int], task_cells: int | None = None) -> DataFrame:
    """Many marginals in one pass over the rows, by partial counts per task; only non-zero cells are shuffled."""
    ship(coded.sparkSession)
    plan = [(m, domain.names(m), domain.shape(m)) for m in masks]
    number = numbers_of(m for m, _, _ in plan)
    sizes, room = {m: domain.size(m) for m, _, _ in plan}, TASK_CELLS if task_cells is None else task_cells

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = Partial(sizes, room, number)
        held, rows = [], 0

        def take() -> None:
            columns = {n: np.concatenate([b.column(n).to_numpy() for b in held]) for n in names}
            for m, own, shape in plan:
                counts.add(m, np.ravel_multi_index([columns[n] for n in own], shape) if own else np.zeros(rows, np.int64))

        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= HELD_ROWS:
                take()
                yield from counts.spill()
                held, rows = [], 0
        if rows:
            take()
        yield from counts.finish()

    names = sorted({n for _, own, _ in plan for n in own}) or [domain.attributes[0].name]
    parts = coded.select(*names).mapInArrow(count, "gamma long, cell long, value long")
    return parts.groupBy("gamma", "cell").agg(F.sum("value").alias("value"))


def roll_up_all(cells: DataFrame, domain: Domain, wanted: dict[int, list[int]]) -> DataFrame:
    """Marginals of subsets from (gamma, cell, value) of larger sets, all in one pass: ``wanted`` lists the subsets that each set of the frame answers."""
    ship(cells.sparkSession)
    axes = {g: domain.axes(g) for g in wanted}
    shapes = {g: domain.shape(g) for g in wanted}
    places = {g: [(m, [axes[g].index(i) for i in domain.axes(m)], domain.shape(m)) for m in own] for g, own in wanted.items()}
    sizes = {m: domain.size(m) for own in wanted.values() for m in own}
    number, mask_of = numbers_of(sizes), {k: g for g, k in numbers_of(wanted).items()}

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = Partial(sizes, TASK_CELLS, number)
        for batch in batches:
            gamma, cell, value = (batch.column(c).to_numpy() for c in ("gamma", "cell", "value"))
            for k in np.unique(gamma).tolist():
                at, g = gamma == k, mask_of[k]
                codes = np.unravel_index(cell[at], shapes[g]) if shapes[g] else ()
                for m, where, shape in places[g]:
                    counts.add(m, np.ravel_multi_index([codes[k] for k in where], shape) if where else np.zeros(int(at.sum()), np.int64), value[at])
            yield from counts.spill()
        yield from counts.finish()

    parts = cells.mapInArrow(sums, "gamma long, cell long, value long")
    return parts.groupBy("gamma", "cell").agg(F.sum("value").alias("value"))


def precollapse(coded: DataFrame, ratio: float = 0.2) -> DataFrame:
    """Distinct coded rows with counts if they are much fewer than rows (by a sketch), else the rows with count 1."""
    names = coded.columns
    facts = coded.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.hash(*names)).alias("d")).first()
    if facts["n"] and facts["d"] < ratio * facts["n"]:
        return coded.groupBy(*names).agg(F.count(F.lit(1)).alias("weight"))
    return coded.withColumn("weight", F.lit(1).cast("long"))


def densify(cells: DataFrame, domain: Domain, masks: Iterable[int]) -> DataFrame:
    """Every cell of every set, 0 where the data has none. Needed before noise: which cells are absent is private."""
    sizes = cells.sparkSession.createDataFrame([(m, domain.size(m)) for m in masks], "gamma long, n long")
    all_cells = sizes.select("gamma", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("cell"))
    return all_cells.join(cells, ["gamma", "cell"], "left").select("gamma", "cell", F.coalesce("value", F.lit(0)).cast("double").alias("value"))


def roll_up(cells: DataFrame, domain: Domain, gamma: int, masks: Iterable[int]) -> DataFrame:
    """Marginals of subsets of ``gamma`` from its own cells."""
    own = cells.where(F.col("gamma") == gamma)
    rest, codes = F.col("cell"), {}
    for i in reversed(domain.axes(gamma)):
        codes[domain.attributes[i].name] = (rest % domain.attributes[i].n).cast("int")
        rest = F.floor(rest / domain.attributes[i].n)
    coded = own.select(*[c.alias(n) for n, c in codes.items()], "value")
    pairs = F.array(*[F.struct(F.lit(m).cast("long").alias("gamma"), domain.cell(m).alias("cell")) for m in masks])
    return coded.select("value", F.explode(pairs).alias("p")).groupBy("p.gamma", "p.cell").agg(F.sum("value").alias("value"))


def tabulate(coded: DataFrame, domain: Domain, masks: Iterable[int], method: str = "auto", dense: bool = True) -> DataFrame:
    """Marginals of all ``masks`` as (gamma, cell, value).

    ``auto`` reads the data once, now, for the sets that are in no other, merged into larger tables where that is cheap, stores those
    tables, and rolls all sets up from them. Where masks do not fit into a long, ``gamma`` is their place among the sorted masks, and only this
    method without ``dense`` takes them.
    """
    masks = sorted(set(masks))
    if method == "auto":
        top = maximal(masks)
        cover = cover_plan(top, domain, 1 << 16) if len(top) <= GREEDY_SETS else block_cover(top, domain, 1 << 12)
        by_size = sorted(cover, key=lambda c: (domain.size(c), c))
        wanted: dict[int, list[int]] = {}
        for m in masks:
            wanted.setdefault(next(c for c in by_size if m & c == m), []).append(m)
        counted = cut(bincount(coded, domain, sorted(wanted)))
        out = roll_up_all(counted, domain, wanted) if any(own != [c] for c, own in wanted.items()) else counted
    else:
        out = {"grouping_sets": grouping_sets, "explode": explode_sets, "bincount": bincount}[method](coded, domain, masks)
    return densify(out, domain, masks) if dense else out


def cube_counts(coded: DataFrame, names: list[str]) -> DataFrame:
    return coded.cube(*names).agg(F.count(F.lit(1)).alias("value"))


def rollup_counts(coded: DataFrame, names: list[str]) -> DataFrame:
    return coded.rollup(*names).agg(F.count(F.lit(1)).alias("value"))


def packed_batches(cells: DataFrame) -> DataFrame:
    """(gamma, cell, value): one row per batch of non-zero cells, its columns as the bytes of arrays."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([batch.column(c).to_numpy(zero_copy_only=False).tobytes()], pa.binary()) for c in names], names=names)

    names = ["gamma", "cell", "value"]
    # counts stay below 2 ** 53, where doubles are exact
    found = cells.where(F.col("value") != 0).select(F.col("gamma").cast("long"), F.col("cell").cast("long"), F.col("value").cast("double"))
    return found.mapInArrow(pack, "gamma binary, cell binary, value binary")


def collect_blocks(cells: DataFrame, domain: Domain, masks: Iterable[int] | None = None, limit: int = 1 << 26) -> dict[int, np.ndarray]:
    """Dense arrays on the driver, for domains whose tables together have at most ``limit`` cells; absent cells are 0.

    Cells arrive packed, partition by partition, so beside the arrays the driver holds one partition of them.
    """
    number = numbers_of(r["gamma"] for r in cells.select("gamma").distinct().collect()) if masks is None else numbers_of(masks)
    if sum(domain.size(m) for m in number) > limit:
        raise ValueError("the marginals are too large for the driver; use the cluster state")
    mask_of = {k: m for m, k in number.items()}
    out = {m: np.zeros(domain.size(m)) for m in number}
    for row in packed_batches(cells).toLocalIterator():
        gamma, cell, value = (np.frombuffer(row[c], kind) for c, kind in (("gamma", np.int64), ("cell", np.int64), ("value", np.float64)))
        order = np.argsort(gamma, kind="stable")
        for own in np.split(order, np.nonzero(np.diff(gamma[order]))[0] + 1):
            out[mask_of[int(gamma[own[0]])]][cell[own]] = value[own]
    return {m: a.reshape(domain.shape(m)) for m, a in out.items()}
