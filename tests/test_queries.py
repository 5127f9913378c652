"""Every query with SQL against DuckDB on the smallest tables; every other one gives rows of a stable schema."""

import pytest

import __spark_entry__ as entry
from tests.compare import database, expected, rows

NAMES = sorted(n for n in entry.queries() if not n.startswith("op") and n != "pipeline")


@pytest.fixture(scope="module")
def con(sf):
    return database(sf)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf, con, name):
    df = entry.queries()[name](spark, sf)
    if name in entry.oracle_sql():
        assert rows(df) == expected(con, entry.oracle_sql()[name])
    else:
        assert df.columns and df.count() >= 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
