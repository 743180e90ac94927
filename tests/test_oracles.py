"""Every query with a DuckDB form gives the same rows at the smallest size; the others give rows."""

import pytest

import __spark_entry__ as entry
from detectlab import plans
from tests import oracle

SF = "/root/testdata/sf0.001"
QUERIES, ORACLES = plans.collect()


@pytest.fixture(scope="module")
def con():
    return oracle.connect(SF)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_duckdb(spark, con, name):
    oracle.compare(QUERIES[name](spark, SF), con, ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, name):
    assert len(QUERIES[name](spark, SF).columns) > 0 and QUERIES[name](spark, SF).count() >= 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(ORACLES) <= set(entry.oracle_sql()) and set(QUERIES) <= set(entry.queries())
