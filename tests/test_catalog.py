"""Every query with SQL gives the same rows as DuckDB; every other one gives rows."""

import pytest

from approxboot import catalog

from .conftest import SF, rows_of

FREE = sorted(set(catalog.QUERIES) - set(catalog.ORACLES))


def test_names_agree():
    assert set(catalog.ORACLES) <= set(catalog.QUERIES)
    assert len(catalog.QUERIES) > 150


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_same_rows_as_sql(spark, duck, name):
    got = catalog.QUERIES[name](spark, SF).toPandas()
    want = duck.execute(catalog.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)


@pytest.mark.parametrize("name", FREE)
def test_gives_rows(spark, name):
    assert catalog.QUERIES[name](spark, SF).toPandas().shape[0] > 0
