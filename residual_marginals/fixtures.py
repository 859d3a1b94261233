"""Declared domains on the given tables, and the frames they code."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.domain import Attribute, Domain
from residual_marginals.sources.io import load

#: For reproducible experiments on public tables; a release of private data needs a secret of its own.
TEST_SECRET = b"test"
#: The printed age by education table (rows: age groups, columns: education).
WORKED_TABLE = ((7, 5, 2), (3, 5, 11), (10, 2, 11), (9, 18, 17))


def coded(name: str, values: tuple[str, ...], attr: str) -> Attribute:
    cases = " ".join(f"WHEN '{v}' THEN {k}" for k, v in enumerate(values))
    return Attribute(attr, len(values), f"CASE {name} {cases} END", values)


FLAG = coded("l_returnflag", ("A", "N", "R"), "flag")
LSTAT = coded("l_linestatus", ("F", "O"), "lstat")
LINENO = Attribute("lineno", 7, "l_linenumber - 1")
DISC = Attribute("disc", 11, "CAST(round(l_discount * 100) AS INT)")
TAX = Attribute("tax", 9, "CAST(round(l_tax * 100) AS INT)")
QTY = Attribute("qty", 10, "CAST(floor((l_quantity - 1) / 5) AS INT)")
OSTAT = coded("o_orderstatus", ("F", "O", "P"), "ostat")
PRIO = Attribute("prio", 5, "CAST(substr(o_orderpriority, 1, 1) AS INT) - 1")
OYEAR = Attribute("oyear", 7, "year(o_orderdate) - 1995")
SEG = coded("c_mktsegment", ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"), "seg")
REGION = Attribute("region", 5, "n_regionkey")
PRICE = Attribute("price", 10, "CAST(least(floor(l_extendedprice / 10500), 9) AS INT)")
REV = Attribute("rev", 10, "CAST(least(floor(l_extendedprice * (1 - l_discount) / 10500), 9) AS INT)")

ORDERS = Domain([OSTAT, PRIO, OYEAR])
LINES = Domain([FLAG, LSTAT, LINENO, DISC, TAX, QTY])
PTYPE = coded("p_type", ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"), "ptype")
SALES = Domain([FLAG, LSTAT, LINENO, DISC, TAX, QTY, OSTAT, PRIO, SEG, REGION, PTYPE, PRICE, REV])
DIALOGUE = Domain([coded("role", ("assistant", "system", "user"), "role"), Attribute("turn", 8, "turn")])
ETYPE = coded("event_type", ("click", "error", "purchase", "signup", "view"), "etype")
ACTIVITY = Domain([ETYPE, Attribute("hour", 24, "hour(ts)"), Attribute("vband", 10, "CAST(least(floor(value / 50), 9) AS INT)")])
MONTHS = "(year({0}) - 1995) * 12 + month({0}) - 1"
WIDE = Domain([
    Attribute("qty", 50, "CAST(l_quantity AS INT) - 1"), Attribute("size", 50, "p_size - 1"), Attribute("brand", 25, "CAST(substr(p_brand, 7) AS INT) - 1"),
    Attribute("nation", 25, "n_nationkey"), DISC, TAX, Attribute("omonth", 80, MONTHS.format("o_orderdate")), Attribute("smonth", 83, MONTHS.format("l_shipdate")), REGION,
])


def bits_domain(n: int = 12) -> Domain:
    return Domain([*(Attribute(f"b{k:02d}", 2, f"CASE WHEN embedding[{k}] > 0 THEN 1 ELSE 0 END") for k in range(n)), Attribute("label", 10, "label")])


def sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lineitem with its order, customer, nation and part."""
    lines, orders, customers, nations, parts = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "nation", "part"))
    with_order = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return with_order.join(customers, F.col("o_custkey") == F.col("c_custkey")).join(nations, F.col("c_nationkey") == F.col("n_nationkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))


def worked(spark: SparkSession) -> DataFrame:
    """The printed table as (age, educ, value)."""
    rows = [(a, e, float(v)) for a, row in enumerate(WORKED_TABLE) for e, v in enumerate(row)]
    return spark.createDataFrame(rows, "age int, educ int, value double")
