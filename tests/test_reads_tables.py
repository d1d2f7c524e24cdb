"""Queries that once made their data up on the driver: Spark reads a given table for them."""

import pytest

import __spark_entry__ as entry
from tests.conftest import SF

LAZY = ("rerank_memory", "regime_accounting", "pareto_front", "paired_t", "memory_accounting", "gsq_design", "bounds_table", "bias_capacity", )


@pytest.mark.parametrize("name", LAZY)
def test_plan_scans_a_table(spark, name):
    df = entry.queries()[name](spark, SF)
    assert df.inputFiles() and df.count() > 0


def test_w16_measures_the_embeddings(spark):
    r = {(x.dataset, x.method, x.metric): x.value for x in entry.queries()["w16_bounds"](spark, SF).where("regime = 'd=64'").collect()}
    assert 0.9 < r["E", "measured", "mse_over_db"] < 1.1
    assert r["E", "measured", "error_quantile"] < r["E", "single", "bound"]


def test_w19_counts_the_embeddings(spark):
    r = {(x.dataset, x.metric): x.value for x in entry.queries()["w19_accounting"](spark, SF).collect()}
    n = spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id % 10 <> 0").count()
    assert r["E", "bits"] == 4 * 64 + 64 + 32 and r["A(2.5)", "mib"] > n * r["E", "bits"] / 8 / (1 << 20)
