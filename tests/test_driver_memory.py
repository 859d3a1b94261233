"""What the driver holds while tables are gathered."""

import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from residual_marginals import experiments
from residual_marginals import fixtures as fx
from residual_marginals.domain import Attribute, Domain
from residual_marginals.lattice import Workload
from residual_marginals.mechanisms import baselines
from residual_marginals.operators import tabulate


def test_gathered_tables_take_little_more_than_their_arrays(spark):
    domain = Domain([Attribute(n, 64, n) for n in "abc"])
    cells = spark.range(64**3, numPartitions=8).select(F.lit(7).cast("long").alias("gamma"), F.col("id").alias("cell"), (F.col("id") % 5).alias("value"))
    tabulate.collect_blocks(cells.where("cell < 100"), domain, [7])
    tracemalloc.start()
    out = tabulate.collect_blocks(cells, domain, [7, 3])
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.array_equal(out[7].ravel(), np.arange(64**3) % 5) and out[7].shape == (64, 64, 64)
    assert out[3].shape == (64, 64) and not out[3].any()
    # 2.1 MB of cells; as rows of numbers they take over ten times that
    assert most < 4 * out[7].nbytes


def test_tradeoff_takes_little_more_than_a_few_copies_of_its_tables(spark):
    domain = Domain([Attribute(n, 64, n) for n in "abc"])
    rows = spark.range(64**3, numPartitions=8).selectExpr("id div 4096 AS a", "id div 64 % 64 AS b", "id % 64 AS c")
    data = {"cube": (rows, domain)}
    run = lambda: experiments.run_tradeoff(spark, data, [1.0], ["direct", "batch"], secret=b"test", trials=1).collect()
    run()
    tracemalloc.start()
    out = run()
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert sorted(r["method"] for r in out) == ["batch", "direct"] and all(r["l1"] > 0 for r in out)
    # a table is 2.1 MB
    assert most < 20 * 64**3 * 8


@pytest.mark.parametrize("domain", [fx.SALES, fx.WIDE], ids=["sales", "wide"])
def test_tables_of_tradeoff_large_are_whole_and_take_little_more_than_their_arrays(spark, sf_dir, duck, domain):
    workload = Workload.all_kway(domain, 3)
    tracemalloc.start()
    out = baselines.truth_of(fx.sales(spark, sf_dir), domain, workload)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    codes = ", ".join(f"{a.coder} AS {a.name}" for a in domain.attributes)
    rows = duck.sql(f"""
        SELECT {codes} FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey
    """).fetchall()
    columns = [np.clip(np.array(c), 0, a.n - 1) for c, a in zip(zip(*rows), domain.attributes)]
    assert sorted(out) == sorted(workload.closure())
    for m, table in out.items():
        cells = np.ravel_multi_index([columns[i] for i in domain.axes(m)], table.shape) if m else np.zeros(len(rows), np.int64)
        assert np.array_equal(table.ravel(), np.bincount(cells, minlength=table.size))
    # as rows of numbers the cells of the 9 long attributes take several times the 29 MB of their arrays
    assert most < 3 * sum(t.nbytes for t in out.values()) + 20_000_000
