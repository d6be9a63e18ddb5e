"""Every query that has SQL gives the same rows as DuckDB; the others run with a stable schema."""

import pytest
from helpers import TINY, duck, rows_of_duck, rows_of_spark

from hypertriad.plans.registry import ORACLES, QUERIES


@pytest.fixture(scope="module")
def con():
    return duck(TINY)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows_as_sql(spark, con, name):
    assert rows_of_spark(QUERIES[name](spark, TINY)) == rows_of_duck(con, ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, name):
    df = QUERIES[name](spark, TINY)
    assert df.count() > 0 and all(df.columns)


def test_entry(spark):
    import __spark_entry__ as entry

    rows = entry.entry(spark).collect()
    assert len(rows) == 20 and all(r["cnt"] > 0 for r in rows)
    assert set(ORACLES) <= set(entry.oracle_sql()) and set(entry.oracle_sql()) <= set(entry.queries())
