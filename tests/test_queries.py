"""Every query with SQL against DuckDB; the others for rows and a stable schema."""

import pytest

import __spark_entry__ as entry
from tests.conftest import SF
from tests.oracle import connect, rows

SQL = {k: v for k, v in entry.oracle_sql().items() if not k.startswith("op") and k != "pipeline"}
KNOWN = entry.queries()


@pytest.fixture(scope="module")
def con():
    return connect(SF)


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, con, name):
    got = KNOWN[name](spark, SF).toPandas()
    want = con.execute(SQL[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["qid", "rank", "vec_id", "score"] and df.count() > 0


def test_each_sql_has_a_query():
    assert set(SQL) <= set(KNOWN)
