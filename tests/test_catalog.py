"""Every query with SQL gives the rows that DuckDB gives; the others run, and hold what is known about them."""

import pytest

from residual_marginals import catalog

#: Experiments of a minute and more; their code runs on smaller domains in test_mechanisms.
LONG = {"ablation", "ablation_bits64", "tradeoff_large", "transform_bench"}


def as_rows(columns, rows):
    keep = sorted(columns)
    return sorted(tuple(str(r[k]) for k in keep) for r in rows)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - LONG))
def test_query(spark, sf_dir, duck, name):
    got = catalog.QUERIES[name](spark, sf_dir)
    rows = got.collect()
    if name in catalog.SQL:
        want = duck.sql(catalog.SQL[name])
        assert sorted(want.columns) == sorted(got.columns)
        assert as_rows(got.columns, rows) == as_rows(want.columns, [dict(zip(want.columns, r)) for r in want.fetchall()])
    else:
        assert rows
