"""Queries by name, with the SQL that gives the same rows on the same tables."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from residual_marginals import experiments, fixtures as fx, measures
from residual_marginals.answer import answer_count
from residual_marginals.domain import encode
from residual_marginals.lattice import Workload, subsets, touched
from residual_marginals.mechanisms import baselines, graphical
from residual_marginals.mechanisms.adaptive import adaptive_release, adaptive_release_cluster, candidate_weights
from residual_marginals.operators import axisops, lazy, measure, noise, reconstruct, residuals, tabulate, tiles
from residual_marginals.operators.axisops import kron_cells
from residual_marginals.operators import blocks
from residual_marginals.plans import planner, privacy
from residual_marginals.plans.schedule import Schedule
from residual_marginals.sources.io import cut, load
from residual_marginals.streaming import marginals as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
AXES = ["ostat", "prio", "oyear"]
KEY = "k1"


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def r6(column: Column | str) -> Column:
    """Rounded to six decimals, without negative zero."""
    return F.round(F.col(column) if isinstance(column, str) else column, 6) + F.lit(0.0)


def rounded(df: DataFrame, *names: str) -> DataFrame:
    for n in names or ("value",):
        df = df.withColumn(n, r6(n))
    return df


S6 = "round({0}, 6) + 0.0"
ORDERS_SQL = "SELECT CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS ostat, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1 AS prio, CAST(year(o_orderdate) - 1995 AS INTEGER) AS oyear FROM orders"
LINES_SQL = """SELECT CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS flag, CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END AS lstat, l_linenumber - 1 AS lineno,
CAST(round(l_discount * 100) AS INTEGER) AS disc, CAST(round(l_tax * 100) AS INTEGER) AS tax, CAST(floor((l_quantity - 1) / 5) AS INTEGER) AS qty FROM lineitem"""
#: Dense orders cells with their codes.
DENSE = f"""coded AS ({ORDERS_SQL}), counted AS (SELECT ostat, prio, oyear, count(*) AS n FROM coded GROUP BY ALL),
grid AS (SELECT CAST(a.range AS INTEGER) AS ostat, CAST(b.range AS INTEGER) AS prio, CAST(c.range AS INTEGER) AS oyear FROM range(3) a, range(5) b, range(7) c),
cells AS (SELECT g.ostat, g.prio, g.oyear, CAST(coalesce(n, 0) AS DOUBLE) AS v FROM grid g LEFT JOIN counted USING (ostat, prio, oyear))"""


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(load(spark, sf_dir, "orders"), fx.ORDERS)


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(load(spark, sf_dir, "lineitem"), fx.LINES)


def dense_orders(spark: SparkSession, sf_dir: str, masks: list[int]) -> DataFrame:
    return tabulate.tabulate(orders(spark, sf_dir), fx.ORDERS, masks)


def orders_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 3-way orders marginal as a relation (ostat, prio, oyear, value)."""
    cells = dense_orders(spark, sf_dir, [7])
    return cells.select(F.floor(F.col("cell") / 35).cast("int").alias("ostat"), (F.floor(F.col("cell") / 7) % 5).cast("int").alias("prio"), (F.col("cell") % 7).cast("int").alias("oyear"), "value")


# --- tabulation ---------------------------------------------------------------------------------------------

ONE_WAY = {
    "flag": ("lineitem", fx.FLAG, "CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END"),
    "lstat": ("lineitem", fx.LSTAT, "CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END"),
    "disc": ("lineitem", fx.DISC, "CAST(round(l_discount * 100) AS INTEGER)"),
    "qty": ("lineitem", fx.QTY, "CAST(floor((l_quantity - 1) / 5) AS INTEGER)"),
    "price": ("lineitem", fx.PRICE, "CAST(least(floor(l_extendedprice / 10500), 9) AS INTEGER)"),
    "prio": ("orders", fx.PRIO, "CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1"),
    "ostat": ("orders", fx.OSTAT, "CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END"),
    "seg": ("customer", fx.SEG, "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END"),
    "etype": ("events", fx.ETYPE, "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END"),
}
for _name, (_table, _attribute, _code) in ONE_WAY.items():
    def _one(spark, sf_dir, table=_table, a=_attribute):
        return tabulate.tabulate_one(load(spark, sf_dir, table).select(F.expr(a.coder).cast("int").alias("code")), ["code"])

    query(f"marginal_1way_{_name}", f"SELECT {_code} AS code, count(*) AS value FROM {_table} GROUP BY 1")(_one)


@query("marginal_2way_flag_lstat", f"SELECT flag, lstat, count(*) AS value FROM ({LINES_SQL}) GROUP BY ALL")
def _(spark, sf_dir):
    return tabulate.tabulate_one(lines(spark, sf_dir), ["flag", "lstat"])


@query("marginal_3way_sales", """SELECT n_regionkey AS region, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS ostat, CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS flag, count(*) AS value
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL""")
def _(spark, sf_dir):
    return tabulate.tabulate_one(encode(fx.sales(spark, sf_dir), fx.SALES), ["region", "ostat", "flag"])


def union_sql(sets: list[int], domain, base: str, dense: bool) -> str:
    """Independent SQL of many marginals as (gamma, cell, value)."""
    parts = []
    for m in sets:
        code = "0"
        for i in domain.axes(m):
            code = f"({code}) * {domain.attributes[i].n} + {domain.attributes[i].name}"
        own = f"SELECT CAST({code} AS BIGINT) AS cell, count(*) AS n FROM rows_ GROUP BY 1"
        if dense:
            parts.append(f"SELECT CAST({m} AS BIGINT) AS gamma, g.range AS cell, CAST(coalesce(n, 0) AS DOUBLE) AS value FROM range({domain.size(m)}) g LEFT JOIN ({own}) c ON c.cell = g.range")
        else:
            parts.append(f"SELECT CAST({m} AS BIGINT) AS gamma, cell, n AS value FROM ({own})")
    return f"WITH rows_ AS ({base}) " + " UNION ALL ".join(parts)


K1, K2, K3 = (Workload.all_kway(fx.LINES, k).sets for k in (1, 2, 3))


@query("marginals_all_1way", union_sql(K1, fx.LINES, LINES_SQL, True))
def _(spark, sf_dir):
    return tabulate.tabulate(lines(spark, sf_dir), fx.LINES, K1)


@query("marginals_all_3way_lines", union_sql(K3, fx.LINES, LINES_SQL, True))
def _(spark, sf_dir):
    return tabulate.tabulate(lines(spark, sf_dir), fx.LINES, K3)


SALES_SQL = f"""SELECT CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS flag, CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END AS lstat, l_linenumber - 1 AS lineno,
CAST(round(l_discount * 100) AS INTEGER) AS disc, CAST(round(l_tax * 100) AS INTEGER) AS tax, CAST(floor((l_quantity - 1) / 5) AS INTEGER) AS qty,
CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS ostat, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1 AS prio,
CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END AS seg, n_regionkey AS region,
CASE p_type WHEN 'ECONOMY' THEN 0 WHEN 'LARGE' THEN 1 WHEN 'MEDIUM' THEN 2 WHEN 'PROMO' THEN 3 WHEN 'SMALL' THEN 4 ELSE 5 END AS ptype,
CAST(least(floor(l_extendedprice / 10500), 9) AS INTEGER) AS price, CAST(least(floor(l_extendedprice * (1 - l_discount) / 10500), 9) AS INTEGER) AS rev,
CAST(l_quantity AS INTEGER) - 1 AS wqty, p_size - 1 AS size, CAST(substr(p_brand, 7) AS INTEGER) - 1 AS brand, n_nationkey AS nation,
CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INTEGER) AS omonth, CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS INTEGER) AS smonth
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey"""


def sets_sql(sets: list[int], domain, base: str) -> str:
    """The same without a scan per set: rows are numbered per set from a list of its attributes and lengths."""
    names = [a.name for a in domain.attributes]
    lists = f"[{', '.join(names)}]"
    steps = f"[{', '.join(str(a.n) for a in domain.attributes)}]"
    masks = ", ".join(map(str, sets))
    picked = "list_filter(range(1, {0} + 1), lambda i: (gamma >> (i - 1)) & 1 = 1)".format(len(names))
    return f"""WITH rows_ AS ({base}), grouped AS (SELECT {lists} AS codes, count(*) AS n FROM rows_ GROUP BY 1),
sets AS (SELECT unnest([{masks}])::BIGINT AS gamma), axes AS (SELECT gamma, {picked} AS ax FROM sets),
hit AS (SELECT gamma, CASE len(ax) WHEN 3 THEN (codes[ax[1]]::BIGINT * {steps}[ax[2]] + codes[ax[2]]) * {steps}[ax[3]] + codes[ax[3]] WHEN 2 THEN codes[ax[1]]::BIGINT * {steps}[ax[2]] + codes[ax[2]] ELSE codes[ax[1]]::BIGINT END AS cell, n FROM grouped, axes)
SELECT gamma, cell, CAST(sum(n) AS BIGINT) AS value FROM hit GROUP BY gamma, cell"""


@query("marginals_all_3way_sales", sets_sql(Workload.all_kway(fx.SALES, 3).sets, fx.SALES, SALES_SQL))
def _(spark, sf_dir):
    return tabulate.tabulate(encode(fx.sales(spark, sf_dir), fx.SALES), fx.SALES, Workload.all_kway(fx.SALES, 3).sets, dense=False)


@query("marginals_all_3way_wide", sets_sql(Workload.all_kway(fx.WIDE, 3).sets, fx.WIDE, f"SELECT * REPLACE (wqty AS qty) FROM ({SALES_SQL})"))
def _(spark, sf_dir):
    return tabulate.tabulate(encode(fx.sales(spark, sf_dir), fx.WIDE), fx.WIDE, Workload.all_kway(fx.WIDE, 3).sets, dense=False)


@query("marginals_all_3way_orders", union_sql([7], fx.ORDERS, ORDERS_SQL, True))
def _(spark, sf_dir):
    return dense_orders(spark, sf_dir, [7])


for _method in ("grouping_sets", "explode", "bincount"):
    def _many(spark, sf_dir, method=_method):
        return tabulate.tabulate(lines(spark, sf_dir), fx.LINES, K2, method, dense=False)

    query(f"tabulate_{_method}", union_sql(K2, fx.LINES, LINES_SQL, False))(_many)


@query("marginal_densified", union_sql([7], fx.LINES, LINES_SQL, True))
def _(spark, sf_dir):
    return tabulate.densify(tabulate.explode_sets(lines(spark, sf_dir), fx.LINES, [7]), fx.LINES, [7])


@query("precollapsed_marginal", f"SELECT flag, qty, count(*) AS value FROM ({LINES_SQL}) GROUP BY ALL")
def _(spark, sf_dir):
    small = tabulate.precollapse(lines(spark, sf_dir).select("flag", "lstat", "qty"))
    return small.groupBy("flag", "qty").agg(F.sum("weight").alias("value"))


@query("marginal_roll_up", f"SELECT CAST(2 AS BIGINT) AS gamma, CAST(prio AS BIGINT) AS cell, CAST(count(*) AS DOUBLE) AS value FROM ({ORDERS_SQL}) GROUP BY prio")
def _(spark, sf_dir):
    return tabulate.roll_up(dense_orders(spark, sf_dir, [7]), fx.ORDERS, 7, [2])


@query("marginal_rollup", f"SELECT ostat, prio, count(*) AS value FROM ({ORDERS_SQL}) GROUP BY ROLLUP (ostat, prio)")
def _(spark, sf_dir):
    return tabulate.rollup_counts(orders(spark, sf_dir), ["ostat", "prio"])


@query("marginal_cube", f"SELECT ostat, prio, count(*) AS value FROM ({ORDERS_SQL}) GROUP BY CUBE (ostat, prio)")
def _(spark, sf_dir):
    return tabulate.cube_counts(orders(spark, sf_dir), ["ostat", "prio"])


# --- axis operations and residuals -----------------------------------------------------------------------------

WORKED_SQL = " UNION ALL ".join(f"SELECT {a} AS age, {e} AS educ, CAST({v} AS DOUBLE) AS v" for a, row in enumerate(fx.WORKED_TABLE) for e, v in enumerate(row))


@query("worked_example", f"""WITH t AS ({WORKED_SQL}), m AS (SELECT age, sum(v) AS v FROM t GROUP BY age)
SELECT 'marginal' AS part, age AS code, v AS value FROM m UNION ALL
SELECT 'residual', age - 1, v - (SELECT v FROM m WHERE age = 0) FROM m WHERE age > 0""")
def _(spark, sf_dir):
    table = fx.worked(spark)
    age = axisops.axis_sum(table, ["age", "educ"], "educ")
    residual = axisops.axis_sub(age, ["age"], "age")
    return age.select(F.lit("marginal").alias("part"), F.col("age").alias("code"), "value").unionByName(residual.select(F.lit("residual").alias("part"), F.col("age").alias("code"), "value"))


@query("axis_sum", f"WITH {DENSE} SELECT ostat, oyear, sum(v) AS value FROM cells GROUP BY ALL")
def _(spark, sf_dir):
    return axisops.axis_sum(orders_cells(spark, sf_dir), AXES, "prio")


@query("axis_sub", f"WITH {DENSE} SELECT a.ostat, a.prio - 1 AS prio, a.oyear, a.v - b.v AS value FROM cells a JOIN cells b ON a.ostat = b.ostat AND a.oyear = b.oyear AND b.prio = 0 WHERE a.prio > 0")
def _(spark, sf_dir):
    return axisops.axis_sub(orders_cells(spark, sf_dir), AXES, "prio")


@query("axis_center", f"""WITH {DENSE}, w AS (SELECT ostat, prio + 1 AS prio, oyear, v FROM cells UNION ALL SELECT ostat, 0, oyear, 0.0 FROM cells WHERE prio = 0)
SELECT ostat, prio, oyear, {S6.format('v - avg(v) OVER (PARTITION BY ostat, oyear)')} AS value FROM w""")
def _(spark, sf_dir):
    return rounded(axisops.axis_center(orders_cells(spark, sf_dir), AXES, "prio", 6))


@query("axis_smear", f"WITH {DENSE}, s AS (SELECT ostat, prio, sum(v) AS v FROM cells GROUP BY ALL) SELECT ostat, prio, CAST(range AS INTEGER) AS oyear, {S6.format('v / 7')} AS value FROM s, range(7)")
def _(spark, sf_dir):
    return rounded(axisops.axis_smear(axisops.axis_sum(orders_cells(spark, sf_dir), AXES, "oyear"), AXES, "oyear", 7))


@query("residual_1way", f"WITH {DENSE}, m AS (SELECT prio, sum(v) AS v FROM cells GROUP BY 1) SELECT prio - 1 AS prio, v - (SELECT v FROM m WHERE prio = 0) AS value FROM m WHERE prio > 0")
def _(spark, sf_dir):
    return residuals.decompose(axisops.axis_sum(axisops.axis_sum(orders_cells(spark, sf_dir), AXES, "ostat"), ["prio", "oyear"], "oyear"), fx.ORDERS, 2, 2)


RES2 = """m AS (SELECT ostat, prio, sum(v) AS v FROM cells GROUP BY ALL), res AS (SELECT a.ostat - 1 AS ostat, a.prio - 1 AS prio, a.v - b.v - c.v + d.v AS value FROM m a
JOIN m b ON b.ostat = 0 AND b.prio = a.prio JOIN m c ON c.prio = 0 AND c.ostat = a.ostat JOIN m d ON d.ostat = 0 AND d.prio = 0 WHERE a.ostat > 0 AND a.prio > 0)"""


@query("residual_2way", f"WITH {DENSE}, {RES2} SELECT * FROM res")
def _(spark, sf_dir):
    return residuals.decompose(axisops.axis_sum(orders_cells(spark, sf_dir), AXES, "oyear"), fx.ORDERS, 3, 3)


@query("residual_from_superset", f"WITH {DENSE}, {RES2} SELECT * FROM res")
def _(spark, sf_dir):
    return residuals.decompose(orders_cells(spark, sf_dir), fx.ORDERS, 7, 3)


def coords_sql(source: str, axes: list[str], last: str) -> str:
    """CTEs that turn ``source`` (axes, v) into residual coordinates, axis by axis."""
    out, before = [], source
    for k, a in enumerate(axes):
        others = ", ".join(x for x in axes if x != a)
        over = f"OVER (PARTITION BY {others})" if others else "OVER ()"
        name = last if k == len(axes) - 1 else f"{last}_{k}"
        out.append(f"{name} AS (SELECT {', '.join(axes)}, CASE WHEN {a} = 0 THEN sum(v) {over} ELSE v - sum(CASE WHEN {a} = 0 THEN v END) {over} END AS v FROM {before})")
        before = name
    return ", ".join(out)


CELL7 = "CAST((ostat * 5 + prio) * 7 + oyear AS BIGINT)"
SUPPORT7 = "CAST((ostat > 0)::INTEGER + 2 * (prio > 0)::INTEGER + 4 * (oyear > 0)::INTEGER AS BIGINT)"


@query("residual_3way", f"WITH {DENSE}, {coords_sql('cells', AXES, 'co')} SELECT ostat - 1 AS ostat, prio - 1 AS prio, oyear - 1 AS oyear, v AS value FROM co WHERE ostat > 0 AND prio > 0 AND oyear > 0")
def _(spark, sf_dir):
    return residuals.decompose(orders_cells(spark, sf_dir), fx.ORDERS, 7, 7)


@query("tiled_residual", f"WITH {DENSE}, {coords_sql('cells', AXES, 'co')} SELECT CAST(((ostat - 1) * 4 + prio - 1) * 6 + oyear - 1 AS BIGINT) AS cell, v AS value FROM co WHERE ostat > 0 AND prio > 0 AND oyear > 0")
def _(spark, sf_dir):
    cells = dense_orders(spark, sf_dir, [7]).select("cell", "value")
    return tiles.to_cells(tiles.decompose(tiles.from_cells(cells, (3, 5, 7)), (3, 5, 7), (0, 1, 2)), (2, 4, 6))


@query("tiled_component", f"WITH {DENSE}, d AS (SELECT ostat, prio, oyear, avg(v) OVER (PARTITION BY ostat, oyear) - avg(v) OVER (PARTITION BY ostat) - avg(v) OVER (PARTITION BY oyear) + avg(v) OVER () AS v FROM cells) SELECT {CELL7} AS cell, {S6.format('v')} AS value FROM d")
def _(spark, sf_dir):
    cells = dense_orders(spark, sf_dir, [7]).select("cell", "value")
    residual = tiles.decompose(tiles.from_cells(cells, (3, 5, 7)), (3, 5, 7), (0, 2))
    return rounded(tiles.to_cells(tiles.reconstruct(residual, (3, 5, 7), (0, 2)), (3, 5, 7)))


@query("nonzero_support", f"WITH {DENSE}, {coords_sql('cells', AXES, 'co')} SELECT CAST(7 AS BIGINT) AS gamma, bit_or({SUPPORT7}) AS support FROM co WHERE v <> 0")
def _(spark, sf_dir):
    """Which attributes any non-zero residual cell depends on."""
    coords = residuals.to_residual_coords(dense_orders(spark, sf_dir, [7]), fx.ORDERS)
    return coords.where("value <> 0").groupBy("gamma").agg(F.bit_or("support").alias("support"))


@query("residual_coords", f"WITH {DENSE}, {coords_sql('cells', AXES, 'co')} SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, {SUPPORT7} AS support, v AS value FROM co")
def _(spark, sf_dir):
    return residuals.to_residual_coords(dense_orders(spark, sf_dir, [7]), fx.ORDERS)


@query("decompose_all", f"""WITH {DENSE}, {coords_sql('cells', AXES, 'co')} SELECT CAST(7 AS BIGINT) AS gamma, {SUPPORT7} AS tau,
CAST(CASE WHEN ostat > 0 THEN ostat - 1 ELSE 0 END * CASE WHEN prio > 0 THEN 4 ELSE 1 END * CASE WHEN oyear > 0 THEN 6 ELSE 1 END + CASE WHEN prio > 0 THEN prio - 1 ELSE 0 END * CASE WHEN oyear > 0 THEN 6 ELSE 1 END + CASE WHEN oyear > 0 THEN oyear - 1 ELSE 0 END AS BIGINT) AS cell, v AS value FROM co""")
def _(spark, sf_dir):
    return residuals.decompose_all(dense_orders(spark, sf_dir, [7]), fx.ORDERS)


DIRECT = f"""SELECT ostat, prio, oyear, {S6.format("avg(v) OVER (PARTITION BY ostat, prio) - avg(v) OVER (PARTITION BY ostat) - avg(v) OVER (PARTITION BY prio) + avg(v) OVER ()")} AS value FROM cells"""


@query("component_direct", f"WITH {DENSE} {DIRECT}")
def _(spark, sf_dir):
    return rounded(axisops.component_direct(orders_cells(spark, sf_dir), AXES, ["ostat", "prio"]))


@query("reconstruct_component", f"WITH {DENSE} {DIRECT}")
def _(spark, sf_dir):
    residual = residuals.decompose(orders_cells(spark, sf_dir), fx.ORDERS, 7, 3)
    return rounded(residuals.reconstruct(residual, fx.ORDERS, 3, 7)).select(*AXES, "value")


@query("roundtrip_exact", f"WITH {DENSE} SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, v AS value FROM cells")
def _(spark, sf_dir):
    return rounded(residuals.from_residual_coords(residuals.to_residual_coords(dense_orders(spark, sf_dir, [7]), fx.ORDERS), fx.ORDERS))


@query("roundtrip_blocks", f"WITH {DENSE} SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, v AS value FROM cells")
def _(spark, sf_dir):
    packed = residuals.pack(dense_orders(spark, sf_dir, [7]))
    back = residuals.map_blocks(residuals.map_blocks(packed, fx.ORDERS, blocks.to_coords, "coords"), fx.ORDERS, blocks.from_coords, "marginal")
    return rounded(residuals.unpack(back)).select("gamma", "cell", "value")


@query("kron_decompose", f"WITH {DENSE}, {RES2} SELECT ostat, prio, 0 AS oyear, value FROM res")
def _(spark, sf_dir):
    parts = dict(zip(AXES, blocks.factors((3, 5, 7), (0, 1))))
    return rounded(kron_cells(orders_cells(spark, sf_dir), AXES, parts))


@query("kron_reconstruct", f"WITH {DENSE} {DIRECT}")
def _(spark, sf_dir):
    residual = residuals.decompose(orders_cells(spark, sf_dir), fx.ORDERS, 7, 3).withColumn("oyear", F.lit(0))
    return rounded(kron_cells(residual, AXES, dict(zip(AXES, blocks.factors((3, 5, 7), (0, 1), inverse=True)))))


@query("axis_sub_mapped", f"WITH {DENSE}, {RES2} SELECT CAST(ostat * 4 + prio AS BIGINT) AS cell, value FROM res")
def _(spark, sf_dir):
    """Differences vector by vector, which whole slices replace."""
    def mapped(block: np.ndarray) -> np.ndarray:
        for axis in range(block.ndim):
            block = blocks.axis_sub_mapped(block, axis)
        return block

    packed = residuals.pack(dense_orders(spark, sf_dir, [3]))
    return residuals.unpack(residuals.map_blocks(packed, fx.ORDERS, mapped, "residual")).select("cell", "value")


@query("axis_order_free", f"WITH {DENSE}, {RES2} SELECT * FROM res")
def _(spark, sf_dir):
    """Steps on different axes in any order; the simplified program sums first."""
    steps = [axisops.Step("sub", "prio"), axisops.Step("sub", "ostat"), axisops.Step("sum", "oyear")]
    program = axisops.AxisProgram(steps, AXES, (3, 5, 7))
    a, b = (p.compile_cells(orders_cells(spark, sf_dir)) for p in (program, program.simplify()))
    return a.intersect(b)


@query("residual_special_cases", f"WITH {DENSE} SELECT 'total' AS what, CAST(count(*) AS BIGINT) AS n, max(v) AS value FROM (SELECT sum(v) AS v FROM cells) UNION ALL SELECT 'length one', 0, NULL UNION ALL SELECT 'total alone', 3, max(v) / 3 FROM (SELECT sum(v) AS v FROM cells)")
def _(spark, sf_dir):
    """The empty residual is the total, an axis of length 1 has no residual, the total alone gives a flat marginal."""
    from residual_marginals.domain import Attribute, Domain

    table = axisops.axis_sum(axisops.axis_sum(orders_cells(spark, sf_dir), AXES, "prio"), ["ostat", "oyear"], "oyear")
    total = residuals.decompose(table, fx.ORDERS, 1, 0)
    one = axisops.AxisProgram.decompose(["x"], (Domain([Attribute("x", 1, "0")]).size(1),), ["x"]).compile_cells(spark.range(1).select(F.lit(0).alias("x"), F.lit(5.0).alias("value")))
    flat = residuals.reconstruct(total, fx.ORDERS, 0, 1)
    parts = {"total": total, "length one": one, "total alone": flat}
    return reduce(DataFrame.unionByName, [f.agg(F.lit(n).alias("what"), F.count(F.lit(1)).alias("n"), F.max("value").alias("value")) for n, f in parts.items()])


# --- noise and measurement --------------------------------------------------------------------------------------

def normal_sql(*columns: str, key: str = KEY) -> str:
    text = " || ':' || ".join([f"'{key}'", *(f"CAST({c} AS VARCHAR)" for c in columns)])
    u = lambda at: f"((('0x' || substr(md5({text}), {at}, 8))::BIGINT + 0.5::DOUBLE) / 4294967296.0::DOUBLE)"
    return f"sqrt(-2.0::DOUBLE * ln({u(1)})) * cos(2.0::DOUBLE * pi() * {u(9)})"


def gumbel_sql(column: str, key: str) -> str:
    return f"-ln(-ln((('0x' || substr(md5('{key}' || ':' || CAST({column} AS VARCHAR)), 1, 8))::BIGINT + 0.5::DOUBLE) / 4294967296.0::DOUBLE))"


@query("keyed_noise", f"SELECT o_orderkey AS cell, {S6.format(normal_sql('o_orderkey'))} AS value FROM orders WHERE o_orderkey IS NOT NULL")
def _(spark, sf_dir):
    """A cell per order."""
    return load(spark, sf_dir, "orders").where("o_orderkey IS NOT NULL").select(F.col("o_orderkey").alias("cell"), r6(noise.keyed_normal(KEY, F.col("o_orderkey"))).alias("value"))


NOISY = lambda gamma, cell, source, s2, key=KEY: f"SELECT *, v + sqrt({s2}::DOUBLE) * ({normal_sql('0', str(gamma), cell, key=key)}) AS nv FROM {source}"


@query("measure_iid", f"WITH {DENSE} SELECT 0 AS round, CAST(7 AS BIGINT) AS gamma, 4.0::DOUBLE AS sigma2, {CELL7} AS cell, {S6.format('nv')} AS value FROM ({NOISY(7, CELL7, 'cells', 4)})")
def _(spark, sf_dir):
    return rounded(measure.measure_marginal(dense_orders(spark, sf_dir, [7]), fx.ORDERS, 4.0, KEY))


PRIO_M = "m AS (SELECT prio, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY 1)"


@query("measure_residual", f"""WITH {DENSE}, {PRIO_M}, n AS ({NOISY(2, 'prio', 'm', 9)})
SELECT 0 AS round, CAST(2 AS BIGINT) AS tau, 9.0::DOUBLE AS sigma2, CAST(prio - 1 AS BIGINT) AS cell, {S6.format('nv - (SELECT nv FROM n WHERE prio = 0)')} AS value FROM n WHERE prio > 0""")
def _(spark, sf_dir):
    return rounded(measure.measure_residual(dense_orders(spark, sf_dir, [2]), fx.ORDERS, 2, 9.0, KEY))


OP_M = "op AS (SELECT ostat, prio, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY ALL)"
OP_N = f"opn AS (SELECT ostat, prio, nv AS v FROM ({NOISY(3, 'CAST(ostat * 5 + prio AS BIGINT)', 'op', 4)}))"
PY_M = "py AS (SELECT prio, oyear, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY ALL)"
PY_N = f"pyn AS (SELECT prio, oyear, nv AS v FROM ({NOISY(6, 'CAST(prio * 7 + oyear AS BIGINT)', 'py', 4)}))"


@query("marginal_to_residuals", f"""WITH {DENSE}, {OP_M}, {OP_N}, {coords_sql('opn', ['ostat', 'prio'], 'co')}
SELECT 0 AS round, CAST(3 AS BIGINT) AS gamma, CAST((ostat > 0)::INTEGER + 2 * (prio > 0)::INTEGER AS BIGINT) AS tau,
CAST(4.0 * CASE WHEN ostat > 0 THEN 1 ELSE 3 END * CASE WHEN prio > 0 THEN 1 ELSE 5 END AS DOUBLE) AS sigma2,
CAST(CASE WHEN ostat > 0 THEN (ostat - 1) * CASE WHEN prio > 0 THEN 4 ELSE 1 END ELSE 0 END + CASE WHEN prio > 0 THEN prio - 1 ELSE 0 END AS BIGINT) AS cell, {S6.format('v')} AS value FROM co""")
def _(spark, sf_dir):
    return rounded(measure.marginal_to_residuals(measure.measure_marginal(dense_orders(spark, sf_dir, [3]), fx.ORDERS, 4.0, KEY), fx.ORDERS))


def measured_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Noisy (ostat, prio) and (prio, oyear) marginals."""
    return measure.measure_marginal(dense_orders(spark, sf_dir, [3, 6]), fx.ORDERS, 4.0, KEY)


#: The shared residuals (total and prio) of both noisy marginals, averaged; variances 60 and 140, 12 and 28.
MERGED = f"""{OP_M}, {OP_N}, {PY_M}, {PY_N}, a AS (SELECT prio, sum(v) AS v FROM opn GROUP BY 1), b AS (SELECT prio, sum(v) AS v FROM pyn GROUP BY 1),
tot AS (SELECT ((SELECT sum(v) FROM a) / 60.0 + (SELECT sum(v) FROM b) / 140.0) / (1 / 60.0 + 1 / 140.0) AS t),
pr AS (SELECT a.prio, ((a.v - (SELECT v FROM a WHERE prio = 0)) / 12.0 + (b.v - (SELECT v FROM b WHERE prio = 0)) / 28.0) / (1 / 12.0 + 1 / 28.0) AS p FROM a JOIN b USING (prio))"""


@query("consolidate", f"""WITH {DENSE}, {MERGED} SELECT CAST(0 AS BIGINT) AS tau, {S6.format('1 / 60.0::DOUBLE + 1 / 140.0::DOUBLE')} AS precision, CAST(0 AS BIGINT) AS cell, {S6.format('t')} AS value FROM tot
UNION ALL SELECT CAST(2 AS BIGINT), {S6.format('1 / 12.0::DOUBLE + 1 / 28.0::DOUBLE')}, CAST(prio - 1 AS BIGINT), {S6.format('p')} FROM pr WHERE prio > 0""")
def _(spark, sf_dir):
    merged = reconstruct.consolidate(measure.marginal_to_residuals(measured_pairs(spark, sf_dir), fx.ORDERS))
    return rounded(merged.where(F.col("tau").isin(0, 2)), "precision", "value")


@query("reconstruct_mle", f"""WITH {DENSE}, {MERGED}, base AS (SELECT prio, (SELECT t FROM tot) / 5 + p - (SELECT avg(p) FROM pr) AS s FROM pr)
SELECT CAST(3 AS BIGINT) AS gamma, CAST(ostat * 5 + prio AS BIGINT) AS cell, {S6.format('opn.v - a.v / 3 + s / 3')} AS value FROM opn JOIN a USING (prio) JOIN base USING (prio)
UNION ALL SELECT CAST(6 AS BIGINT), CAST(prio * 7 + oyear AS BIGINT), {S6.format('pyn.v - b.v / 7 + s / 7')} FROM pyn JOIN b USING (prio) JOIN base USING (prio)""")
def _(spark, sf_dir):
    return rounded(reconstruct.reconstruct_from(fx.ORDERS, [3, 6], marginals=measured_pairs(spark, sf_dir)))


@query("reconstruct_mixture", SQL["reconstruct_mle"])
def _(spark, sf_dir):
    """One input as a noisy marginal, the other as noisy residuals."""
    pairs = measured_pairs(spark, sf_dir)
    residual_part = measure.marginal_to_residuals(pairs.where("gamma = 6"), fx.ORDERS)
    return rounded(reconstruct.reconstruct_from(fx.ORDERS, [3, 6], marginals=pairs.where("gamma = 3"), measured_residuals=residual_part))


@query("estimate_update", SQL["consolidate"])
def _(spark, sf_dir):
    """Estimates from one marginal, averaged with what a second one tells."""
    pairs = measured_pairs(spark, sf_dir)
    first, second = (measure.marginal_to_residuals(pairs.where(F.col("gamma") == g), fx.ORDERS).where(F.col("tau").isin(0, 2)) for g in (3, 6))
    return rounded(reconstruct.update_estimate(reconstruct.consolidate(first), second), "precision", "value")


@query("touched_marginals", "SELECT CAST(t.range AS BIGINT) AS alpha, count(*) AS touched FROM range(64) t JOIN (SELECT range AS g FROM range(64) WHERE bit_count(range) = 3) ON g & t.range = t.range GROUP BY 1")
def _(spark, sf_dir):
    """How many 3-way marginals of six attributes a change of each residual reaches."""
    reached = [(a, touched(a, K3)) for a in Workload(K3).closure()]
    return spark.createDataFrame(reached, "alpha long, touched long")


def exact_estimates(spark: SparkSession, sf_dir: str, taus: list[int]) -> DataFrame:
    cells = residuals.decompose_all(dense_orders(spark, sf_dir, taus), fx.ORDERS).where(F.col("tau") == F.col("gamma"))
    return cut(cells.select("tau", F.lit(1.0).alias("precision"), "cell", "value"))


ADDITIVE = """m1 AS (SELECT ostat, sum(v) AS v FROM cells GROUP BY 1), m2 AS (SELECT prio, sum(v) AS v FROM cells GROUP BY 1), m3 AS (SELECT oyear, sum(v) AS v FROM cells GROUP BY 1), t AS (SELECT sum(v) AS n FROM cells)"""


@query("unmeasured_zero", f"""WITH {DENSE}, {ADDITIVE} SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, {S6.format('m1.v / 35 + m2.v / 21 + m3.v / 15 - 2 * n / 105')} AS value FROM m1, m2, m3, t""")
def _(spark, sf_dir):
    known = exact_estimates(spark, sf_dir, [0, 1, 2, 4])
    every = reconstruct.with_unmeasured(known, fx.ORDERS, subsets(7))
    return rounded(reconstruct.reconstruct_all(every, fx.ORDERS, [7]))


@query("unmeasured_antijoin", "SELECT CAST(t AS BIGINT) AS tau FROM (VALUES (3), (5), (6), (7)) x(t)")
def _(spark, sf_dir):
    wanted = spark.createDataFrame([(t,) for t in subsets(7)], "tau long")
    return wanted.join(exact_estimates(spark, sf_dir, [0, 1, 2, 4]), "tau", "left_anti")


@query("consistency_check", "SELECT 0.0::DOUBLE AS gap")
def _(spark, sf_dir):
    both = cut(reconstruct.reconstruct_from(fx.ORDERS, [3, 6], marginals=measured_pairs(spark, sf_dir)))
    return spark.createDataFrame([(round(reconstruct.consistency_gap(both, fx.ORDERS, 3, 6), 6) + 0.0,)], "gap double")


ADD2 = f"""{ADDITIVE}, m12 AS (SELECT ostat, prio, sum(v) AS v FROM cells GROUP BY ALL)"""
LAZY_SQL = f"""WITH {DENSE}, {ADD2} SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, {S6.format('m12.v / 7 + m3.v / 15 - n / 105')} AS value FROM m12, m3, t"""


def lazily(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Marginal 7 from 1-way residuals, then residual {ostat, prio} added lazily; and the full rebuild."""
    known = exact_estimates(spark, sf_dir, [0, 1, 2, 4])
    before = residuals.pack(reconstruct.reconstruct_all(known, fx.ORDERS, [7, 4]))
    new = exact_estimates(spark, sf_dir, [3])
    delta = {3: np.array([r["value"] for r in new.orderBy("cell").collect()]).reshape(2, 4)}
    after = residuals.unpack(lazy.lazy_round(before, fx.ORDERS, delta)).select("gamma", "cell", "value")
    return after, lazy.full_rebuild(known.unionByName(new), fx.ORDERS, [7, 4])


@query("lazy_update", LAZY_SQL)
def _(spark, sf_dir):
    return rounded(lazily(spark, sf_dir)[0].where("gamma = 7"))


@query("lazy_update_cells", LAZY_SQL)
def _(spark, sf_dir):
    known = exact_estimates(spark, sf_dir, [0, 1, 2, 4])
    before = cut(reconstruct.reconstruct_all(known, fx.ORDERS, [7, 4]))
    delta = exact_estimates(spark, sf_dir, [3]).select("tau", "cell", "value")
    return rounded(lazy.lazy_cells(before, fx.ORDERS, delta).where("gamma = 7"))


@query("lazy_vs_full_diff", "SELECT 0.0::DOUBLE AS diff")
def _(spark, sf_dir):
    after, full = lazily(spark, sf_dir)
    gap = measures.l1_error(full, after).agg(r6(F.max("l1")).alias("diff"))
    return gap


# --- plans --------------------------------------------------------------------------------------------------------

SUBSETS7 = """SELECT t AS tau, CASE WHEN t & 1 = 1 THEN 2 / 3.0::DOUBLE ELSE 1 END * CASE WHEN t & 2 = 2 THEN 4 / 5.0::DOUBLE ELSE 1 END * CASE WHEN t & 4 = 4 THEN 6 / 7.0::DOUBLE ELSE 1 END AS p,
CASE WHEN t & 1 = 1 THEN 1 ELSE 1 / 3.0::DOUBLE END * CASE WHEN t & 2 = 2 THEN 1 ELSE 1 / 5.0::DOUBLE END * CASE WHEN t & 4 = 4 THEN 1 ELSE 1 / 7.0::DOUBLE END AS r FROM (SELECT range AS t FROM range(8))"""
PRIOR = {0: 2.0, 1: 0.4, 2: 0.05, 4: 0.02, 6: 0.3}
PRIOR_SQL = "CASE tau " + " ".join(f"WHEN {t} THEN {a}::DOUBLE" for t, a in PRIOR.items()) + " ELSE 0.0::DOUBLE END"


# plans for the domain that each month of the orders spans
SPANS_SQL = """spans AS (SELECT CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INTEGER) AS month, count(DISTINCT o_orderstatus) AS n0, count(DISTINCT o_orderpriority) AS n1, count(DISTINCT day(o_orderdate)) AS n2
FROM orders WHERE o_orderdate IS NOT NULL AND o_orderstatus IS NOT NULL AND o_orderpriority IS NOT NULL GROUP BY 1)"""
#: Residuals of a month's 3-way marginal; one on an axis of length 1 has no cells.
MONTHS_SQL = f"""{SPANS_SQL}, taus AS (SELECT * FROM (SELECT *, CASE WHEN tau & 1 = 1 THEN (n0 - 1) / n0::DOUBLE ELSE 1 END * CASE WHEN tau & 2 = 2 THEN (n1 - 1) / n1::DOUBLE ELSE 1 END * CASE WHEN tau & 4 = 4 THEN (n2 - 1) / n2::DOUBLE ELSE 1 END AS p,
CASE WHEN tau & 1 = 1 THEN 1 ELSE 1 / n0::DOUBLE END * CASE WHEN tau & 2 = 2 THEN 1 ELSE 1 / n1::DOUBLE END * CASE WHEN tau & 4 = 4 THEN 1 ELSE 1 / n2::DOUBLE END AS r FROM spans, (SELECT range AS tau FROM range(8))) WHERE p > 0)"""
MONTH_WATER_SQL = f"""{MONTHS_SQL}, g AS (SELECT * FROM (VALUES (0.5::DOUBLE)) x(rho)), s AS (SELECT *, {PRIOR_SQL} AS a FROM taus, g),
w AS (SELECT *, (2 * rho + sum(p * a) OVER o) / sum(p * r) OVER o AS lvl, lead(a / r) OVER (PARTITION BY month, rho ORDER BY a / r, tau) AS nxt FROM s WINDOW o AS (PARTITION BY month, rho ORDER BY a / r, tau ROWS UNBOUNDED PRECEDING)),
c AS (SELECT month, rho, min(lvl) AS c FROM w WHERE nxt IS NULL OR lvl <= nxt GROUP BY month, rho)"""


def by_month(spark: SparkSession, sf_dir: str, of: Callable, schema: str) -> DataFrame:
    """What ``of`` gives for the domain that each month's orders span: (month, *schema), worked out in the tasks."""
    found = load(spark, sf_dir, "orders").dropna(subset=["o_orderdate", "o_orderstatus", "o_orderpriority"])
    month = F.expr("CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INT)").alias("month")
    seen = found.select(month, "o_orderstatus", "o_orderpriority", F.dayofmonth("o_orderdate").alias("oday")).distinct()
    spans = seen.groupBy("month").agg(*[F.count_distinct(c).alias(f"n{k}") for k, c in enumerate(("o_orderstatus", "o_orderpriority", "oday"))])
    # a number of its own, so that months stay dealt over the tasks; equal spans meet in one
    return planner.by_domain(spans.repartition(16, "n0", "n1", "n2"), ["n0", "n1", "n2"], of, schema)


@query("coefficients_pv", f"WITH {MONTHS_SQL} SELECT month, tau, {S6.format('p')} AS p, {S6.format('p * r * r')} AS v, {S6.format('r')} AS r FROM taus")
def _(spark, sf_dir):
    return rounded(by_month(spark, sf_dir, lambda d: [(x.tau, float(x.p), float(x.v), float(x.r)) for x in planner.coefficients(7, d)], "tau long, p double, v double, r double"), "p", "v", "r")


@query("junction_sizes", f"WITH {MONTHS_SQL} SELECT month, model, cells * 8 / 1048576::DOUBLE AS mb FROM (SELECT month, unnest(['chain', 'cycle', 'loose']) AS model, unnest([n0 * n1 + n1 * n2, n0 * n1 * n2, n0 + n1 + n2]) AS cells FROM spans)")
def _(spark, sf_dir):
    """Megabytes of graphical models: pairs in a chain, in a cycle (one clique), single attributes."""
    models = {"chain": [3, 6], "cycle": [3, 6, 5], "loose": [1, 2, 4]}
    return by_month(spark, sf_dir, lambda d: [(n, float(graphical.junction_size_mb(m, d))) for n, m in models.items()], "model string, mb double")


@query("iid_plan", f"WITH {MONTHS_SQL} SELECT month, tau, {S6.format('1 / r')} AS sigma2 FROM taus")
def _(spark, sf_dir):
    return rounded(by_month(spark, sf_dir, lambda d: [(x.tau, float(x.sigma2)) for x in planner.iid_plan(7, d, 0.5)], "tau long, sigma2 double"), "sigma2")


@query("closed_form_plan", f"""WITH {MONTHS_SQL}, s AS (SELECT *, CASE tau WHEN 0 THEN 0.001::DOUBLE ELSE 0.0::DOUBLE END AS a FROM taus), c AS (SELECT month, (1.0 + sum(p * a)) / sum(p * r) AS c FROM s GROUP BY month)
SELECT month, tau, round(c * r - a, 10) + 0.0 AS new_precision FROM s JOIN c USING (month)""")
def _(spark, sf_dir):
    """Ten decimals: 1.001 over 16 or 80 stands half way between two numbers of six."""

    def plan(d):
        rows = [planner.Row(x.gamma, x.tau, x.p, x.v, x.r, 0.001 if x.tau == 0 else 0.0) for x in planner.coefficients(7, d)]
        return [(x.tau, float(b)) for x, b in zip(rows, planner.closed_form(rows, 0.5))]

    made = by_month(spark, sf_dir, plan, "tau long, new_precision double")
    return made.withColumn("new_precision", F.round("new_precision", 10) + F.lit(0.0))


WATER = f"""s AS (SELECT *, {PRIOR_SQL} AS a FROM ({SUBSETS7})),
w AS (SELECT *, a / r AS q, (1.0::DOUBLE + sum(p * a) OVER o) / sum(p * r) OVER o AS lvl, lead(a / r) OVER (ORDER BY a / r, tau) AS nxt, row_number() OVER (ORDER BY a / r, tau) AS k FROM s WINDOW o AS (ORDER BY a / r, tau ROWS UNBOUNDED PRECEDING)),
c AS (SELECT lvl AS c FROM w WHERE nxt IS NULL OR lvl <= nxt ORDER BY k LIMIT 1)"""


@query("water_fill_plan", f"WITH {WATER} SELECT tau, {S6.format('greatest(0.0::DOUBLE, c * r - a)')} AS new_precision FROM s, c")
def _(spark, sf_dir):
    return rounded(planner.to_df(spark, planner.conditional_plan(7, fx.ORDERS, PRIOR, 0.5)), "new_precision").select("tau", "new_precision")


@query("plan_pruned", f"WITH {WATER} SELECT tau FROM s, c WHERE c * r - a > 0.3 * c * r")
def _(spark, sf_dir):
    return planner.to_df(spark, planner.conditional_plan(7, fx.ORDERS, PRIOR, 0.5, 0.3, redistribute=False)).where("keep").select("tau")


@query("residual_rho", f"WITH {WATER} SELECT {S6.format('sum(p * greatest(0.0::DOUBLE, c * r - a)) / 2')} AS rho FROM s, c")
def _(spark, sf_dir):
    plan = planner.to_df(spark, planner.conditional_plan(7, fx.ORDERS, PRIOR, 0.5))
    return plan.agg(r6(F.sum(F.col("p") * F.col("new_precision")) / 2).alias("rho"))


@query("expected_mse", f"""WITH {MONTH_WATER_SQL} SELECT month, {S6.format('sum(p * r * r / greatest(a, c * r))')} AS mse, {S6.format('any_value(n0 * n1 * n2) * sum(p * r * r / greatest(a, c * r))')} AS sse,
{S6.format('any_value(n0 * n1 * n2) * sqrt(2 / pi()) * sqrt(sum(p * r * r / greatest(a, c * r)))')} AS l1 FROM s JOIN c USING (month, rho) GROUP BY month""")
def _(spark, sf_dir):
    def errors(d):
        known = {x.tau: x.prior + x.new for x in planner.conditional_plan(7, d, PRIOR, 0.5)}
        return [tuple(float(f(7, d, known)) for f in (planner.expected_mse, planner.expected_sse, planner.expected_l1))]

    return rounded(by_month(spark, sf_dir, errors, "mse double, sse double, l1 double"), "mse", "sse", "l1")


PAIRS_SQL = f"""g AS (SELECT * FROM (VALUES (3), (5), (6)) x(gamma)), z AS (SELECT gamma, tau, p, p * r_ * r_ AS v FROM (SELECT gamma, tau, p,
CASE WHEN gamma & 1 = 1 AND tau & 1 = 0 THEN 1 / 3.0::DOUBLE ELSE 1 END * CASE WHEN gamma & 2 = 2 AND tau & 2 = 0 THEN 1 / 5.0::DOUBLE ELSE 1 END * CASE WHEN gamma & 4 = 4 AND tau & 4 = 0 THEN 1 / 7.0::DOUBLE ELSE 1 END AS r_
FROM g JOIN ({SUBSETS7}) ON tau & gamma = tau)), q AS (SELECT tau, min(p) AS p, sum(v) AS v FROM z GROUP BY tau)"""


MONTH_PAIRS_SQL = f"""{MONTHS_SQL}, z AS (SELECT month, tau, p, p * r_ * r_ AS v FROM (SELECT month, tau, p,
CASE WHEN gamma & 1 = 1 AND tau & 1 = 0 THEN 1 / n0::DOUBLE ELSE 1 END * CASE WHEN gamma & 2 = 2 AND tau & 2 = 0 THEN 1 / n1::DOUBLE ELSE 1 END * CASE WHEN gamma & 4 = 4 AND tau & 4 = 0 THEN 1 / n2::DOUBLE ELSE 1 END AS r_
FROM (SELECT * FROM (VALUES (3), (5), (6)) x(gamma)) JOIN taus ON tau & gamma = tau)), q AS (SELECT month, tau, min(p) AS p, sum(v) AS v FROM z GROUP BY month, tau)"""


@query("batch_plan_sum", f"WITH {MONTH_PAIRS_SQL} SELECT month, tau, {S6.format('sqrt(v / p) / sum(sqrt(v * p)) OVER (PARTITION BY month)')} AS new_precision FROM q")
def _(spark, sf_dir):
    return rounded(by_month(spark, sf_dir, lambda d: [(x.tau, float(x.new)) for x in planner.batch_plan(Workload.all_kway(d, 2), d, 0.5)], "tau long, new_precision double"), "new_precision")


@query("batch_plan_max")
def _(spark, sf_dir):
    return by_month(spark, sf_dir, lambda d: [(x.tau, float(x.new)) for x in planner.batch_plan(Workload.all_kway(d, 2), d, 0.5, objective="max")], "tau long, new_precision double")


@query("schedule_initial", "SELECT round(sqrt(8 / (0.9 * 0.5)), 6) + 0.0 AS sigma, round(sqrt(0.4 * 0.5 / 8), 6) + 0.0 AS epsilon, round(0.5 * 0.5 / 8, 6) + 0.0 AS round_rho")
def _(spark, sf_dir):
    s = Schedule.initial(0.5, 8)
    return rounded(spark.createDataFrame([(s.sigma, s.epsilon, s.round_rho)], "sigma double, epsilon double, round_rho double"), "sigma", "epsilon", "round_rho")


BLOCKS_SQL = """WITH c AS (SELECT o_custkey // 6 AS block, count(*) AS c FROM orders WHERE o_custkey IS NOT NULL AND o_orderstatus IS NOT NULL AND o_orderpriority IS NOT NULL GROUP BY o_custkey // 6, o_orderstatus, o_orderpriority),
m AS (SELECT block, sum(abs(c - n / 15.0::DOUBLE)) + (15 - count(*)) * any_value(n) / 15.0::DOUBLE AS moved FROM c JOIN (SELECT block, sum(c)::DOUBLE AS n FROM c GROUP BY 1) USING (block) GROUP BY block)"""


@query("anneal_step", f"{BLOCKS_SQL} SELECT block, {S6.format('moved')} AS moved, CASE WHEN moved < sqrt(2 / pi()) * 2 * 15 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS sigma, CASE WHEN moved < sqrt(2 / pi()) * 2 * 15 THEN 0.2::DOUBLE ELSE 0.1::DOUBLE END AS epsilon FROM m")
def _(spark, sf_dir):
    """The step after a first round for every six customers: their 15 cells of status and priority move from an even spread to what their orders are."""

    def annealed(batches):
        for batch in batches:
            steps = [Schedule(2.0, 0.1) for _ in range(len(batch))]
            for s, moved in zip(steps, batch["moved"]):
                s.anneal(moved, 15)
            yield batch.assign(sigma=[s.sigma for s in steps], epsilon=[s.epsilon for s in steps])

    found = load(spark, sf_dir, "orders").dropna(subset=["o_custkey", "o_orderstatus", "o_orderpriority"])
    cells = found.groupBy(F.expr("o_custkey div 6").alias("block"), "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("c"))
    own = cells.groupBy("block").agg(F.sum("c").alias("n"), F.collect_list("c").alias("cs"))
    moved = F.aggregate("cs", F.lit(0.0), lambda a, c: a + F.abs(c - F.col("n") / 15)) + (15 - F.size("cs")) * F.col("n") / 15
    return rounded(own.select("block", moved.alias("moved")).mapInPandas(annealed, "block long, moved double, sigma double, epsilon double"), "moved")


@query("rho_to_eps", "SELECT rho, round(rho + 2 * sqrt(rho * ln(1e9)), 6) + 0.0 AS eps FROM (VALUES (0.01::DOUBLE), (0.1::DOUBLE), (1.0::DOUBLE)) x(rho)")
def _(spark, sf_dir):
    return rounded(spark.createDataFrame([(r, privacy.rho_to_eps(r, 1e-9, "simple")) for r in (0.01, 0.1, 1.0)], "rho double, eps double"), "eps")


@query("rho_to_eps_tight", """WITH r AS (SELECT * FROM (VALUES (0.01::DOUBLE), (0.1::DOUBLE), (1.0::DOUBLE)) x(rho)), o AS (SELECT 1 + pow(10::DOUBLE, -4 + 12 * range / 5999::DOUBLE) AS a FROM range(6000))
SELECT rho, round(min(a * rho + (ln(1e9::DOUBLE) - ln(a - 1) + a * ln(1 - 1 / a)) / (a - 1)), 6) + 0.0 AS eps, round(rho, 6) + 0.0 AS back FROM r, o GROUP BY rho""")
def _(spark, sf_dir):
    rows = [(r, privacy.rho_to_eps(r, 1e-9), privacy.eps_to_rho(privacy.rho_to_eps(r, 1e-9), 1e-9)) for r in (0.01, 0.1, 1.0)]
    return rounded(spark.createDataFrame(rows, "rho double, eps double, back double"), "eps", "back")


# --- selection and errors -------------------------------------------------------------------------------------------

UNIFORM = """u AS (SELECT CAST(1 AS BIGINT) AS gamma, CAST(ostat AS BIGINT) AS cell, sum(v) AS v FROM cells GROUP BY ostat UNION ALL SELECT 2, prio, sum(v) FROM cells GROUP BY prio UNION ALL SELECT 4, oyear, sum(v) FROM cells GROUP BY oyear
UNION ALL SELECT 3, ostat * 5 + prio, sum(v) FROM cells GROUP BY ostat, prio UNION ALL SELECT 5, ostat * 7 + oyear, sum(v) FROM cells GROUP BY ostat, oyear UNION ALL SELECT 6, prio * 7 + oyear, sum(v) FROM cells GROUP BY prio, oyear),
sc AS (SELECT gamma, CASE WHEN gamma IN (1, 2, 4) THEN 2 ELSE 4 END * (sum(abs(v - t)) - sqrt(2 / pi()) * 3 * count(*)) AS score FROM (SELECT *, sum(v) OVER (PARTITION BY gamma) / count(*) OVER (PARTITION BY gamma) AS t FROM u) GROUP BY gamma)"""


def scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    sets = [1, 2, 3, 4, 5, 6]
    truth = residuals.pack(dense_orders(spark, sf_dir, sets))
    total = exact_estimates(spark, sf_dir, [0])
    flat = residuals.pack(reconstruct.reconstruct_all(total, fx.ORDERS, sets))
    from residual_marginals.mechanisms.adaptive import score_blocks

    return score_blocks(truth, flat, fx.ORDERS, candidate_weights(sets, Workload.all_kway(fx.ORDERS, 2)), 3.0)


@query("score_candidates", f"WITH {DENSE}, {UNIFORM} SELECT gamma, {S6.format('score')} AS score FROM sc")
def _(spark, sf_dir):
    return rounded(scored(spark, sf_dir), "score")


@query("exp_select", f"WITH {DENSE}, {UNIFORM}, n AS (SELECT gamma, score, score * (0.001 / 8) + ({gumbel_sql('gamma', 'sel')}) AS noisy FROM sc) SELECT gamma, {S6.format('score')} AS score, {S6.format('noisy')} AS noisy FROM n ORDER BY n.noisy DESC, gamma LIMIT 1")
def _(spark, sf_dir):
    return rounded(privacy.exp_select(scored(spark, sf_dir), 0.001, 4.0, "sel"), "score", "noisy")


ERR = f"WITH {DENSE}, e AS ({NOISY(7, CELL7, 'cells', 4)})"


def truth_and_noisy(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    truth = cut(dense_orders(spark, sf_dir, [7]))
    return truth, measure.measure_marginal(truth, fx.ORDERS, 4.0, KEY).select("gamma", "cell", "value")


@query("l1_error", f"{ERR} SELECT CAST(7 AS BIGINT) AS gamma, {S6.format('sum(abs(nv - v))')} AS l1, count(*) AS n_cells FROM e")
def _(spark, sf_dir):
    return rounded(measures.l1_error(*truth_and_noisy(spark, sf_dir)), "l1")


@query("l1_error_by_records", f"{ERR} SELECT CAST(7 AS BIGINT) AS gamma, {S6.format('2 * sum(abs(nv - v)) / sum(v)')} AS l1, count(*) AS n_cells FROM e")
def _(spark, sf_dir):
    return rounded(measures.l1_error(*truth_and_noisy(spark, sf_dir), weights={7: 2.0}, normalise="records"), "l1").select("gamma", "l1", "n_cells")


@query("l2_error", f"{ERR} SELECT CAST(7 AS BIGINT) AS gamma, {S6.format('sum((nv - v) * (nv - v))')} AS sse, {S6.format('avg((nv - v) * (nv - v))')} AS mse FROM e")
def _(spark, sf_dir):
    return rounded(measures.l2_error(*truth_and_noisy(spark, sf_dir)), "sse", "mse")


NOISY_PAIRS = " UNION ALL ".join(
    f"SELECT CAST({g} AS BIGINT) AS gamma, cell, v, nv FROM ({NOISY(g, 'cell', f'(SELECT CAST({c} AS BIGINT) AS cell, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY 1)', 4)})"
    for g, c in ((3, "ostat * 5 + prio"), (5, "ostat * 7 + oyear"), (6, "prio * 7 + oyear"))
)


def noisy_pairs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    truth = cut(dense_orders(spark, sf_dir, [3, 5, 6]))
    return truth, measure.measure_marginal(truth, fx.ORDERS, 4.0, KEY).select("gamma", "cell", "value")


@query("largest_errors", f"WITH {DENSE}, e AS ({NOISY_PAIRS}) SELECT gamma, cell, {S6.format('abs(nv - v)')} AS error FROM e ORDER BY abs(nv - v) DESC, gamma, cell LIMIT 10")
def _(spark, sf_dir):
    return rounded(measures.largest_errors(*noisy_pairs(spark, sf_dir)), "error")


@query("worst_marginals", f"""WITH {DENSE}, e AS ({NOISY_PAIRS}), l AS (SELECT gamma, sum(abs(nv - v)) AS l1, count(*) AS n_cells FROM e GROUP BY gamma)
SELECT gamma, {S6.format('l1')} AS l1, n_cells, CAST(row_number() OVER (ORDER BY l1 DESC, gamma) AS INTEGER) AS place, CAST(ntile(4) OVER (ORDER BY l1 DESC, gamma) AS INTEGER) AS part FROM l QUALIFY place <= 2""")
def _(spark, sf_dir):
    return rounded(measures.worst_marginals(*noisy_pairs(spark, sf_dir), k=2), "l1")


@query("error_profile", f"WITH {DENSE}, e AS ({NOISY_PAIRS}) SELECT gamma, {S6.format('stddev_pop(abs(nv - v))')} AS spread, {S6.format('quantile_disc(abs(nv - v), 0.5)')} AS median, {S6.format('max(abs(nv - v))')} AS most FROM e GROUP BY gamma")
def _(spark, sf_dir):
    return rounded(measures.error_profile(*noisy_pairs(spark, sf_dir)), "spread", "median", "most")


@query("postprocessed", f"{ERR}, q AS (SELECT *, greatest(nv, 0.0::DOUBLE) AS c FROM e) SELECT CAST(7 AS BIGINT) AS gamma, {CELL7} AS cell, {S6.format('c * (SELECT sum(nv) FROM q) / (SELECT sum(c) FROM q)')} AS value FROM q")
def _(spark, sf_dir):
    return rounded(reconstruct.postprocess(truth_and_noisy(spark, sf_dir)[1]))


@query("likelihood_loss", f"""WITH {DENSE}, {PRIO_M}, n AS ({NOISY(2, 'prio', 'm', 9)}), d AS (SELECT prio, (nv - v) AS x FROM n), f AS (SELECT x - (SELECT x FROM d WHERE prio = 0) AS y FROM d)
SELECT {S6.format('sum((y - m) * (y - m)) / 9')} AS loss FROM f, (SELECT avg(y) AS m FROM f)""")
def _(spark, sf_dir):
    z, t = (np.array([r["value"] for r in f.orderBy("cell").collect()]) for f in (measure.measure_residual(dense_orders(spark, sf_dir, [2]), fx.ORDERS, 2, 9.0, KEY), exact_estimates(spark, sf_dir, [2])))
    return rounded(spark.createDataFrame([(measures.weighted_residual_loss([(z, 9.0)], t),)], "loss double"), "loss")


# --- joins, streams, other tables ------------------------------------------------------------------------------------

@query("range_band_join", "SELECT b AS band, count(*) AS value FROM lineitem JOIN (SELECT range AS b, range * 20000.0 AS lo, (range + 1) * 20000.0 AS hi FROM range(6)) ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY b")
def _(spark, sf_dir):
    bands = spark.range(6).select(F.col("id").alias("band"), (F.col("id") * 20000.0).alias("lo"), ((F.col("id") + 1) * 20000.0).alias("hi"))
    price = load(spark, sf_dir, "lineitem").select("l_extendedprice")
    return price.join(F.broadcast(bands), (F.col("l_extendedprice") >= F.col("lo")) & (F.col("l_extendedprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("value"))


@query("asof_estimate", f"""WITH {DENSE}, m AS (SELECT prio, count(*) AS n FROM coded GROUP BY 1), e AS (SELECT range AS round, prio, n * (range + 1) AS value FROM m, range(3)) SELECT prio, max_by(value, round) AS value FROM e WHERE round <= 1 GROUP BY prio""")
def _(spark, sf_dir):
    counts = tabulate.tabulate_one(orders(spark, sf_dir), ["prio"])
    history = counts.crossJoin(F.broadcast(spark.range(3))).select("prio", F.col("id").alias("round"), (F.col("value") * (F.col("id") + 1)).alias("value"))
    return history.where("round <= 1").groupBy("prio").agg(F.max_by("value", "round").alias("value"))


EV = "SELECT ts, user_id, event_id, CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS etype FROM events"


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.coded_events(load(spark, sf_dir, "events"), fx.ACTIVITY)


@query("windowed_marginal_events", f"SELECT date_trunc('day', ts) AS window_start, CAST(1 AS BIGINT) AS gamma, CAST(etype AS BIGINT) AS cell, count(*) AS value FROM ({EV}) GROUP BY ALL")
def _(spark, sf_dir):
    out = streams.stream_marginals(activity(spark, sf_dir), fx.ACTIVITY, [1], watermark=None)
    return out.withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@query("sliding_marginal_events", f"""SELECT ws AS window_start, CAST(1 AS BIGINT) AS gamma, CAST(etype AS BIGINT) AS cell, count(*) AS value FROM (
SELECT date_trunc('day', ts) - (k * INTERVAL 1 DAY) AS ws, etype FROM ({EV}), (SELECT unnest([0, 1]) AS k)) GROUP BY ALL""")
def _(spark, sf_dir):
    out = streams.stream_marginals(activity(spark, sf_dir), fx.ACTIVITY, [1], "2 days", "1 day", None)
    return out.withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@query("session_marginal_events", f"""WITH o AS (SELECT user_id, etype, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id, etype ORDER BY ts) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS cut, lag(ts) OVER (PARTITION BY user_id, etype ORDER BY ts) IS NULL AS f FROM ({EV}))
SELECT etype, CAST(sum(cut + f::INTEGER) AS BIGINT) AS sessions, count(*) AS events FROM o GROUP BY etype""")
def _(spark, sf_dir):
    return streams.session_marginals(activity(spark, sf_dir), "etype")


@query("bounded_contribution", f"""WITH r AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY substr(md5('bound:' || CAST(event_id AS VARCHAR)), 1, 8), event_id) AS k FROM ({EV})) SELECT etype, count(*) AS value FROM r WHERE k <= 10 GROUP BY etype""")
def _(spark, sf_dir):
    kept = streams.bounded_contribution(load(spark, sf_dir, "events"), 10)
    return tabulate.tabulate_one(encode(kept, fx.ACTIVITY), ["etype"])


@query("recent_events", """SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS recent,
round(cume_dist() OVER (PARTITION BY event_type ORDER BY value), 6) + 0.0 AS share FROM events""")
def _(spark, sf_dir):
    """Events of the same user in the day before, and the share of events of the type that are no larger."""
    events = load(spark, sf_dir, "events").withColumn("at", F.unix_timestamp(F.date_trunc("second", F.col("ts").cast("timestamp"))))
    day = Window.partitionBy("user_id").orderBy("at").rangeBetween(-86400, 0)
    share = F.cume_dist().over(Window.partitionBy("event_type").orderBy("value"))
    return events.select("event_id", F.count(F.lit(1)).over(day).alias("recent"), r6(share).alias("share"))


@query("late_events", """WITH o AS (SELECT ts, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events)
SELECT coalesce(epoch(date_trunc('second', seen))::BIGINT - epoch(date_trunc('second', ts))::BIGINT > 3600, false) AS late, count(*) AS rows FROM o GROUP BY 1""")
def _(spark, sf_dir):
    return streams.late_rows(load(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts")), 3600, 1000)


@query("stream_available_now", f"SELECT CAST(1 AS BIGINT) AS gamma, CAST(etype AS BIGINT) AS cell, count(*) AS value FROM ({EV}) GROUP BY etype")
def _(spark, sf_dir):
    import uuid

    from residual_marginals.sources.io import shared_path

    name = f"stream_{uuid.uuid4().hex}"
    schema = load(spark, sf_dir, "events").schema
    events = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    counts = streams.stream_marginals(streams.coded_events(events, fx.ACTIVITY), fx.ACTIVITY, [1])
    running = counts.writeStream.outputMode("complete").format("memory").queryName(name).option("checkpointLocation", shared_path(spark)).trigger(availableNow=True).start()
    running.awaitTermination()
    return spark.table(name).groupBy("gamma", "cell").agg(F.sum("value").alias("value"))


@query("doc_meta_marginal", "SELECT lang, coalesce(quality, 2) AS quality, count(*) AS value FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY ALL")
def _(spark, sf_dir):
    docs, labels = load(spark, sf_dir, "documents").select("doc_id", "lang"), load(spark, sf_dir, "labels").select("doc_id", "quality")
    return docs.join(labels, "doc_id", "left").groupBy("lang", F.coalesce("quality", F.lit(2)).alias("quality")).agg(F.count(F.lit(1)).alias("value"))


DLG = "t AS (SELECT CASE role WHEN 'assistant' THEN 0 WHEN 'system' THEN 1 ELSE 2 END AS a, least(turn, 7) AS b FROM conversations), m AS (SELECT g.range AS a, h.range AS b, CAST((SELECT count(*) FROM t WHERE t.a = g.range AND t.b = h.range) AS DOUBLE) AS v FROM range(3) g, range(8) h)"


@query("dialogue_residual", f"WITH {DLG}, {coords_sql('m', ['a', 'b'], 'co')} SELECT CAST(3 AS BIGINT) AS tau, CAST((a - 1) * 7 + b - 1 AS BIGINT) AS cell, v AS value FROM co WHERE a > 0 AND b > 0")
def _(spark, sf_dir):
    coded = encode(load(spark, sf_dir, "conversations"), fx.DIALOGUE)
    return residuals.decompose_all(tabulate.tabulate(coded, fx.DIALOGUE, [3]), fx.DIALOGUE).where("tau = 3").select("tau", "cell", "value")


@query("bits_marginal", "SELECT (embedding[1] > 0)::INTEGER AS b00, (embedding[2] > 0)::INTEGER AS b01, label, count(*) AS value FROM embeddings GROUP BY ALL")
def _(spark, sf_dir):
    return tabulate.tabulate_one(encode(load(spark, sf_dir, "embeddings"), fx.bits_domain(12)), ["b00", "b01", "label"])


@query("pages_scheme_band", "SELECT split_part(url, ':', 1) AS scheme, CAST(least(floor(length(html) / 2000), 9) AS INTEGER) AS band, count(*) AS value FROM pages GROUP BY ALL")
def _(spark, sf_dir):
    return load(spark, sf_dir, "pages").groupBy(F.split("url", ":")[0].alias("scheme"), F.least(F.floor(F.length("html") / 2000), F.lit(9)).cast("int").alias("band")).agg(F.count(F.lit(1)).alias("value"))


@query("benchmark_length_band", "SELECT CAST(floor(length(text) / 100) AS INTEGER) AS band, count(*) AS value FROM benchmark GROUP BY ALL")
def _(spark, sf_dir):
    return load(spark, sf_dir, "benchmark").groupBy(F.floor(F.length("text") / 100).cast("int").alias("band")).agg(F.count(F.lit(1)).alias("value"))


@query("props_json_marginal", "SELECT CAST(least(floor(CAST(json_extract_string(props, '$.k') AS INTEGER) / 10), 9) AS INTEGER) AS band, count(*) AS value FROM events GROUP BY ALL")
def _(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy(F.least(F.floor(F.get_json_object("props", "$.k").cast("int") / 10), F.lit(9)).cast("int").alias("band")).agg(F.count(F.lit(1)).alias("value"))


# --- mechanisms and experiments (random by key, or not in SQL) ---------------------------------------------------------

DIRECT_SQL = " UNION ALL ".join(
    f"SELECT CAST({g} AS BIGINT) AS gamma, cell, {S6.format('nv')} AS value FROM ({NOISY(g, 'cell', f'(SELECT CAST({c} AS BIGINT) AS cell, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY 1)', 3)})"
    for g, c in ((3, "ostat * 5 + prio"), (5, "ostat * 7 + oyear"), (6, "prio * 7 + oyear"))
)


@query("direct_release_cells", f"WITH {DENSE} {DIRECT_SQL}")
def _(spark, sf_dir):
    # rho 0.5 over three marginals: variance 3 each
    return rounded(measure.measure_marginal(dense_orders(spark, sf_dir, [3, 5, 6]), fx.ORDERS, 3.0, KEY)).select("gamma", "cell", "value")


PAIRS = Workload.all_kway(fx.ORDERS, 2)


def raw_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders")


SECRET = fx.TEST_SECRET
PUBLIC = noise.PublicNoise()


def release(spark: SparkSession, sf_dir: str, **options):
    return adaptive_release(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS, 0.5, secret=SECRET, **options)


@query("adaptive_release")
def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All 2-way marginals of orders, released adaptively."""
    return release(spark, sf_dir).marginals(spark)


@query("adaptive_trace")
def _(spark, sf_dir):
    return release(spark, sf_dir).trace(spark).drop("seconds")


@query("adaptive_release_cluster")
def _(spark, sf_dir):
    return residuals.unpack(adaptive_release_cluster(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS, 0.5, secret=SECRET)[0])


@query("release_invariants", """SELECT * FROM (VALUES ('cluster', 0.5::DOUBLE, 0.0::DOUBLE, true), ('local', 0.5::DOUBLE, 0.0::DOUBLE, true)) x(state, spent, gap, likely)""")
def _(spark, sf_dir):
    """What holds for any release: the budget is spent, answers agree on shared attributes, totals lie within eight standard deviations."""
    out = release(spark, sf_dir)
    packed, ledger, _ = adaptive_release_cluster(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS, 0.5, secret=SECRET)
    found = {r["gamma"]: np.array(r["values"]).reshape(fx.ORDERS.shape(r["gamma"])) for r in packed.collect()}
    records = raw_orders(spark, sf_dir).count()
    rows = []
    for state, tables, spent in (("local", out.state.marginals, out.ledger.total), ("cluster", found, ledger.total)):
        gap = max(np.abs(tables[3].sum(axis=1) - tables[5].sum(axis=1)).max(), np.abs(tables[3].sum(axis=0) - tables[6].sum(axis=1)).max())
        rows.append((state, round(spent, 6) + 0.0, round(float(gap), 6) + 0.0, bool(abs(tables[3].sum() - records) < 8 / math.sqrt(out.state.precision[0]))))
    return spark.createDataFrame(rows, "state string, spent double, gap double, likely boolean")


def public_normal(key: str, cell: str) -> str:
    """Noise of the public test source: key and cell."""
    return normal_sql(cell, key=key)


NAMES = {1: ("ostat",), 2: ("prio",), 4: ("oyear",), 3: ("ostat", "prio"), 5: ("ostat", "oyear"), 6: ("prio", "oyear")}
LENGTHS = {"ostat": 3, "prio": 5, "oyear": 7}


def own_cell(names: tuple[str, ...]) -> str:
    code = names[0]
    for n in names[1:]:
        code = f"({code}) * {LENGTHS[n]} + {n}"
    return f"CAST({code} AS BIGINT)"


def centred(names: tuple[str, ...]) -> str:
    """Value v of a noisy table less its axis means: the component without the lengths of other axes."""
    if len(names) == 1:
        return "v - avg(v) OVER ()"
    return f"v - avg(v) OVER (PARTITION BY {names[0]}) - avg(v) OVER (PARTITION BY {names[1]}) + avg(v) OVER ()"


def released_sql(scale: dict[int, str], key: str) -> str:
    """CTEs n0 and n1 to n6: noisy tables of all sets of at most two attributes (the first as the total t, the others centred), and the answers ``a``."""
    parts = [f"n0 AS (SELECT sum(v) + sqrt({scale[0]}) * ({public_normal(f'{key}:0', '0')}) AS t FROM cells)"]
    for m, names in NAMES.items():
        own = ", ".join(names)
        noisy = f"SELECT {own}, v + sqrt({scale[m]}) * ({public_normal(f'{key}:{m}', own_cell(names))}) AS v FROM (SELECT {own}, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY {own})"
        parts.append(f"n{m} AS (SELECT {own}, {centred(names)} AS c FROM ({noisy}))")
    answers = []
    for m in (3, 5, 6):
        a, b = NAMES[m]
        one, two = (next(k for k, x in NAMES.items() if x == (n,)) for n in (a, b))
        answers.append(
            f"SELECT CAST({m} AS BIGINT) AS gamma, {own_cell((a, b))} AS cell, t / {LENGTHS[a] * LENGTHS[b]} + n{one}.c / {LENGTHS[b]} + n{two}.c / {LENGTHS[a]} + n{m}.c AS v FROM n{m} JOIN n{one} USING ({a}) JOIN n{two} USING ({b}), n0"
        )
    return ", ".join(parts) + ", a AS (" + " UNION ALL ".join(answers) + ")"


#: Plan of the batch release at rho 0.5, and the expected error per cell of each answer.
BATCH = f"""{PAIRS_SQL}, plan AS (SELECT tau, sqrt(v / p) / sum(sqrt(v * p)) OVER () AS x FROM q), err AS (SELECT gamma, sqrt(sum(z.v / x)) AS sd FROM z JOIN plan USING (tau) GROUP BY gamma)"""
BATCH_RELEASE = f"WITH {DENSE}, {BATCH}, {released_sql({m: f'(SELECT 1 / x FROM plan WHERE tau = {m})' for m in (0, *NAMES)}, 'batch')}"


def public_batch(spark: SparkSession, sf_dir: str):
    return baselines.batch_release(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS, 0.5, secret=PUBLIC)


@query("batch_release", f"{BATCH_RELEASE} SELECT gamma, cell, {S6.format('v')} AS value, {S6.format('sd')} AS sd FROM a JOIN err USING (gamma)")
def _(spark, sf_dir):
    return rounded(public_batch(spark, sf_dir).marginals(spark), "value", "sd")


@query("answer_count", f"{BATCH_RELEASE} SELECT {S6.format('sum(v)')} AS value, {S6.format('2 * max(sd)')} AS sd FROM a JOIN err USING (gamma) WHERE gamma = 3 AND cell IN (0, 5)")
def _(spark, sf_dir):
    return rounded(spark.createDataFrame([answer_count(public_batch(spark, sf_dir), {"ostat": {0, 1}, "prio": {0}})], "value double, sd double"), "value", "sd")


#: One given marginal (ostat, prio), half of rho 0.5 on the 1-way tables (variance 4 for the two attributes that it has), half on its plan.
SEQUENCE = f"""{", ".join(f"m{m} AS (SELECT {NAMES[m][0]}, v + sqrt(4.0::DOUBLE) * ({public_normal(f'run:init:{m}', own_cell(NAMES[m]))}) AS v FROM (SELECT {NAMES[m][0]}, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY 1))" for m in (1, 2))},
t0 AS (SELECT ((SELECT sum(v) FROM m1) / 12 + (SELECT sum(v) FROM m2) / 20) / (1 / 12.0::DOUBLE + 1 / 20.0::DOUBLE) AS t),
s AS (SELECT * FROM (VALUES (0, 1.0::DOUBLE, 1 / 15.0::DOUBLE, 1 / 12.0::DOUBLE + 1 / 20.0::DOUBLE), (1, 2 / 3.0::DOUBLE, 1 / 5.0::DOUBLE, 0.25::DOUBLE), (2, 4 / 5.0::DOUBLE, 1 / 3.0::DOUBLE, 0.25::DOUBLE), (3, 8 / 15.0::DOUBLE, 1.0::DOUBLE, 0.0::DOUBLE)) x(tau, p, r, a)),
w AS (SELECT *, (0.5::DOUBLE + sum(p * a) OVER o) / sum(p * r) OVER o AS lvl, lead(a / r) OVER (ORDER BY a / r, tau) AS nxt, row_number() OVER (ORDER BY a / r, tau) AS k FROM s WINDOW o AS (ORDER BY a / r, tau ROWS UNBOUNDED PRECEDING)),
c AS (SELECT lvl AS c FROM w WHERE nxt IS NULL OR lvl <= nxt ORDER BY k LIMIT 1), x AS (SELECT tau, a, greatest(0.0::DOUBLE, c * r - a) AS x FROM s, c),
{", ".join(f"k{m} AS (SELECT {', '.join(NAMES[m])}, v + ({public_normal(f'run:0:{m}', own_cell(NAMES[m]))}) / sqrt((SELECT greatest(x, 1e-300) FROM x WHERE tau = {m})) AS v FROM (SELECT {', '.join(NAMES[m])}, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY ALL))" for m in (1, 2, 3))},
{", ".join(f"c{m} AS (SELECT {NAMES[m][0]}, (a * (m{m}.v - avg(m{m}.v) OVER ()) + x * (k{m}.v - avg(k{m}.v) OVER ())) / (a + x) AS c FROM m{m} JOIN k{m} USING ({NAMES[m][0]}), x WHERE tau = {m})" for m in (1, 2))},
c3 AS (SELECT ostat, prio, {centred(NAMES[3])} AS c FROM k3)"""


@query("adaptive_one_round", f"WITH {DENSE}, {SEQUENCE} SELECT CAST(3 AS BIGINT) AS gamma, {own_cell(NAMES[3])} AS cell, {S6.format('t / 15 + c1.c / 5 + c2.c / 3 + c3.c')} AS value FROM c3 JOIN c1 USING (ostat) JOIN c2 USING (prio), t0")
def _(spark, sf_dir):
    """One round on a given marginal: 1-way tables, the plan given what they tell, the residuals it keeps, their averages."""
    out = adaptive_release(raw_orders(spark, sf_dir), fx.ORDERS, Workload([3]), 0.5, secret=PUBLIC, sequence=[3], min_gain=1e-9)
    return rounded(out.marginals(spark).drop("sd"))


@query("adaptive_ledger", """SELECT CAST(k AS INTEGER) AS step, CASE WHEN k < 3 THEN 'one-way' ELSE 'measure' END AS kind, round(0.25 / 3, 6) + 0.0 AS rho, ['ostat', 'prio', 'oyear', '6', '3', '5'][k + 1] AS note FROM (SELECT range AS k FROM range(6))""")
def _(spark, sf_dir):
    return rounded(release(spark, sf_dir, sequence=[6, 3, 5]).ledger.to_df(spark), "rho")


def listed(spark: SparkSession, answers: dict[int, np.ndarray]) -> DataFrame:
    return spark.createDataFrame([(g, k, float(v)) for g, a in answers.items() for k, v in enumerate(a.ravel())], "gamma long, cell long, value double")


@query("direct_release", f"WITH {DENSE} " + " UNION ALL ".join(
    f"SELECT CAST({m} AS BIGINT) AS gamma, {own_cell(NAMES[m])} AS cell, round(v + sqrt(3.0::DOUBLE) * ({public_normal(f'direct:{m}', own_cell(NAMES[m]))}), 6) + 0.0 AS value FROM (SELECT {', '.join(NAMES[m])}, CAST(sum(v) AS DOUBLE) AS v FROM cells GROUP BY ALL)" for m in (3, 5, 6)))
def _(spark, sf_dir):
    # rho 0.5 over three marginals: variance 3 each
    return rounded(listed(spark, baselines.direct_release(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS, 0.5, secret=PUBLIC)[0]))


@query("adaptive_graphical")
def _(spark, sf_dir):
    truth = baselines.truth_of(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS)
    return listed(spark, graphical.adaptive_graphical(truth, fx.ORDERS, PAIRS, 0.5, secret=SECRET)[0])


@query("graphical_reconstruct", f"""WITH {DENSE}, {OP_M}, {PY_M}, p AS (SELECT prio, sum(v) AS v FROM cells GROUP BY prio)
SELECT CAST(3 AS BIGINT) AS gamma, CAST(ostat * 5 + prio AS BIGINT) AS cell, round(v, 1) + 0.0 AS value FROM op UNION ALL SELECT CAST(6 AS BIGINT), CAST(prio * 7 + oyear AS BIGINT), round(v, 1) + 0.0 FROM py
UNION ALL SELECT CAST(5 AS BIGINT), CAST(ostat * 7 + oyear AS BIGINT), round(sum(op.v * py.v / p.v), 1) + 0.0 FROM op JOIN py USING (prio) JOIN p USING (prio) GROUP BY ostat, oyear""")
def _(spark, sf_dir):
    # two exact marginals that share an attribute: the model is their product over it
    truth = baselines.truth_of(raw_orders(spark, sf_dir), fx.ORDERS, PAIRS)
    answers = graphical.graphical_reconstruct([(3, truth[3], 1.0), (6, truth[6], 1.0)], fx.ORDERS, [3, 6, 5], float(truth[0]))
    return listed(spark, {g: np.round(a, 1) + 0.0 for g, a in answers.items()})


def full_orders(spark: SparkSession, sf_dir: str) -> np.ndarray:
    return tabulate.collect_blocks(dense_orders(spark, sf_dir, [7]), fx.ORDERS, [7])[7]


@query("mw_release")
def _(spark, sf_dir):
    return listed(spark, baselines.multiplicative_weights(full_orders(spark, sf_dir), fx.ORDERS, PAIRS.sets, 0.5, secret=SECRET)[0])


@query("identity_strategy", f"WITH {DENSE}, n AS (SELECT ostat, prio, oyear, v + ({public_normal('identity', CELL7)}) AS v FROM cells) " + " UNION ALL ".join(
    f"SELECT CAST({m} AS BIGINT) AS gamma, {own_cell(NAMES[m])} AS cell, round(sum(v), 6) + 0.0 AS value FROM n GROUP BY {', '.join(NAMES[m])}" for m in (3, 5, 6)))
def _(spark, sf_dir):
    # rho 0.5: variance 1
    return rounded(listed(spark, baselines.identity_strategy(full_orders(spark, sf_dir), fx.ORDERS, PAIRS.sets, 0.5, secret=PUBLIC)[0]))


def ablation_data(spark: SparkSession, sf_dir: str) -> dict:
    return {"sales": (fx.sales(spark, sf_dir), fx.SALES), "bits": (load(spark, sf_dir, "embeddings"), fx.bits_domain(12)), "wide": (fx.sales(spark, sf_dir), fx.WIDE)}


@query("ablation")
def _(spark, sf_dir):
    """All 3-way marginals of 13, 13 and 9 attributes; the lazy strategies in five trials, the rebuilding one, whose error is that of lazy_iid, in one."""
    return experiments.run_ablation(spark, ablation_data(spark, sf_dir), secret=SECRET, trials={"lazy_conditional": 5, "lazy_iid": 5, "full_iid": 1})


@query("ablation_speedups")
def _(spark, sf_dir):
    return measures.speedup_table(experiments.run_ablation(spark, {"lines": (load(spark, sf_dir, "lineitem"), fx.LINES)}, secret=SECRET), "full_iid")


@query("ablation_bits64")
def _(spark, sf_dir):
    """All 43,680 triples of 64 bits and a label, by the strategy that can do it."""
    data = {"bits64": (load(spark, sf_dir, "embeddings"), fx.bits_domain(64))}
    return experiments.run_ablation(spark, data, secret=SECRET, trials=1, strategies=["lazy_conditional"])


@query("resumed_release", "SELECT true AS same_rounds, true AS same_answers, 0.5::DOUBLE AS spent")
def _(spark, sf_dir):
    """A release that stops after two rounds, is stored and goes on draws the same noise as one that was never stopped."""
    from residual_marginals.mechanisms.adaptive import load_progress, save_progress
    from residual_marginals.sources.io import shared_path

    path, whole = shared_path(spark), release(spark, sf_dir)
    save_progress(spark, release(spark, sf_dir, max_rounds=2), path)
    stored = load_progress(spark, path, fx.ORDERS, PAIRS, 0.5)
    done = release(spark, sf_dir, progress=stored)
    same = all(np.allclose(done.state.marginals[g], whole.state.marginals[g]) for g in PAIRS.sets)
    rows = [([r[1] for r in done.rounds] == [r[1] for r in whole.rounds], bool(same), round(done.ledger.total, 6) + 0.0)]
    return spark.createDataFrame(rows, "same_rounds boolean, same_answers boolean, spent double")


@query("release_costs")
def _(spark, sf_dir):
    """Jobs, stages, rows, bytes and time of a release from the tables on."""
    costs = measures.spark_costs(spark, lambda: adaptive_release(fx.sales(spark, sf_dir), fx.SALES, Workload.all_kway(fx.SALES, 3), 0.5, secret=SECRET))
    return spark.createDataFrame([tuple(type_(costs[name]) for name, type_ in zip((c.split()[0] for c in measures.COSTS.split(", ")), (int, int, int, int, int, int, float, float)))], measures.COSTS)


@query("marginal_pivot", f"SELECT ostat, " + ", ".join(f"count(*) FILTER (prio = {k}) AS p{k}" for k in range(5)) + f" FROM ({ORDERS_SQL}) GROUP BY ostat")
def _(spark, sf_dir):
    wide = orders(spark, sf_dir).groupBy("ostat").pivot("prio", list(range(5))).count()
    return wide.select("ostat", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"p{k}") for k in range(5)])


LINE_SET = "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END + CASE WHEN l_linestatus = 'F' THEN 2 ELSE 0 END + CASE WHEN l_discount > 0.05 THEN 4 ELSE 0 END"


@query("closure_by_sql", f"SELECT CAST(g.range AS BIGINT) AS gamma, count(DISTINCT l_orderkey) AS orders FROM (SELECT l_orderkey, {LINE_SET} AS mask FROM lineitem) JOIN range(8) g ON mask & g.range = g.range GROUP BY 1")
def _(spark, sf_dir):
    """A line stands for the set of what holds for it; in the closures of how many orders each set is."""
    from residual_marginals.functions.sqlfunctions import register

    register(spark)
    # the sets of an order as bits of one number, so that orders of equal sets are closed once
    own = load(spark, sf_dir, "lineitem").where("l_orderkey IS NOT NULL").groupBy("l_orderkey").agg(F.expr(f"bit_or(shiftleft(1L, {LINE_SET}))").alias("bits"))
    lists = own.groupBy("bits").agg(F.count(F.lit(1)).alias("orders")).selectExpr("filter(sequence(0L, 7L), m -> getbit(bits, CAST(m AS INT)) = 1) AS masks", "orders")
    return spark.sql("SELECT gamma, sum(orders) AS orders FROM {lists} l, LATERAL rm_closure(l.masks) GROUP BY gamma", lists=lists)


@query("workload_set_operations", "SELECT * FROM (VALUES ('both', CAST(3 AS BIGINT)), ('first only', CAST(5 AS BIGINT)), ('first only', CAST(6 AS BIGINT)), ('second only', CAST(7 AS BIGINT))) x(part, gamma)")
def _(spark, sf_dir):
    a, b = PAIRS.to_df(spark).select("gamma"), spark.createDataFrame([(3,), (7,)], "gamma long")
    parts = {"both": a.intersect(b), "first only": a.exceptAll(b), "second only": b.subtract(a)}
    out = [d.select(F.lit(n).alias("part"), "gamma") for n, d in parts.items()]
    return out[0].unionByName(out[1]).unionByName(out[2])


BUDGETS = [0.1, 0.3, 1.0, 3.0, 10.0]


@query("tradeoff")
def _(spark, sf_dir):
    """All 3-way marginals of the lines, five budgets, five trials; the graphical model may take 0.05 of the 0.32 MB that the whole domain would."""
    data = {"lines": (load(spark, sf_dir, "lineitem"), fx.LINES)}
    return experiments.run_tradeoff(spark, data, BUDGETS, ["adaptive", "batch", "direct", "graphical"], secret=SECRET, model_mb=0.05)


@query("tradeoff_large")
def _(spark, sf_dir):
    """The same on 13 attributes and on 9 long ones, whose whole domains no graphical model of 50 MB holds; budgets up to 1000 on the latter."""
    sales = experiments.run_tradeoff(spark, {"sales": (fx.sales(spark, sf_dir), fx.SALES)}, BUDGETS, ["adaptive", "batch", "direct"], secret=SECRET)
    wide = experiments.run_tradeoff(spark, {"wide": (fx.sales(spark, sf_dir), fx.WIDE)}, [1.0, 10.0, 100.0, 1000.0], ["adaptive", "batch", "direct"], secret=SECRET, trials=2)
    return sales.unionByName(wide)


@query("tradeoff_relative")
def _(spark, sf_dir):
    return measures.relative_to(QUERIES["tradeoff"](spark, sf_dir))


@query("model_size_sweep")
def _(spark, sf_dir):
    return experiments.size_sweep(spark, load(spark, sf_dir, "lineitem"), fx.LINES, [0.005, 0.05, 0.5], secret=SECRET)


@query("transform_bench")
def _(spark, sf_dir):
    shapes = [(2, 16), (3, 16), (4, 16), (5, 16), (6, 16), *((3, n) for n in (2, 4, 8, 32, 64, 128, 256))]
    return experiments.run_transform_bench(spark, shapes, repeats=3, relational_cells=300)


@query("transform_tiled")
def _(spark, sf_dir):
    """Arrays in tiles on the executors, also beyond what one process should hold; degree 7 takes 2 GB as numbers and is for a cluster."""
    return experiments.run_tiled_bench(spark, [(4, 16), (5, 16)])


NO_GAP = "0.0::DOUBLE"


@query("noise_plan_check", f"""WITH {MONTH_WATER_SQL.replace('(0.5::DOUBLE)', '(0.01::DOUBLE), (0.5::DOUBLE), (5.0::DOUBLE)')}
SELECT month, rho, {NO_GAP} AS left_over, {NO_GAP} AS gap, {S6.format('CASE WHEN bool_or(greatest(a, c * r) = 0) THEN NULL ELSE sum(p * r * r / greatest(a, c * r)) END')} AS error, true AS best FROM s JOIN c USING (month, rho) GROUP BY month, rho""")
def _(spark, sf_dir):
    """Budget left over, violation of the optimality conditions, expected error, and that a numeric search finds nothing better."""

    def checks(d):
        rows = []
        for rho in (0.01, 0.5, 5.0):
            plan = planner.conditional_plan(7, d, PRIOR, rho)
            left, gap = planner.plan_check(plan, rho)
            found = planner.numeric_plan(plan, rho, 500)
            other = math.fsum(x.v / (x.prior + n) if x.prior + n > 0 else math.inf for x, n in zip(plan, found))
            rows.append((rho, float(left), float(gap), float(planner.plan_error(plan)), bool(other >= planner.plan_error(plan) * (1 - 1e-9))))
        return rows

    return rounded(by_month(spark, sf_dir, checks, "rho double, left_over double, gap double, error double, best boolean"), "left_over", "gap", "error")
