"""Every query with SQL gives the rows that DuckDB gives."""

import oracle
import pytest

import __spark_entry__ as entry

SQL = entry.oracle_sql()


@pytest.fixture(scope="module")
def duck(small):
    return oracle.connect(small)


@pytest.mark.parametrize("name", [n for n in SQL if not n.startswith("op") and n != "pipeline"])
def test_matches_sql(spark, duck, small, name):
    mine = entry.queries()[name](spark, small).toPandas()
    theirs = duck.execute(SQL[name]).df()
    assert sorted(mine.columns) == sorted(theirs.columns)
    assert oracle.rows(mine) == oracle.rows(theirs)


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_every_query_is_callable():
    assert set(SQL) <= set(entry.queries())
