"""Queries that once made their data up read a given table."""

import pytest

from residual_marginals import catalog

READ = {
    "noise_plan_check": "orders",
    "keyed_noise": "orders",
    "junction_sizes": "orders",
    "iid_plan": "orders",
    "expected_mse": "orders",
    "coefficients_pv": "orders",
    "closure_by_sql": "lineitem",
    "closed_form_plan": "orders",
    "batch_plan_sum": "orders",
    "batch_plan_max": "orders",
    "anneal_step": "orders",
}


@pytest.mark.parametrize("name", sorted(READ))
def test_reads_its_table(spark, sf_dir, name):
    read = catalog.QUERIES[name](spark, sf_dir).inputFiles()
    assert {f.rsplit("/", 1)[1] for f in read} == {f"{READ[name]}.parquet"}
