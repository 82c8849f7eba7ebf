"""Queries read a given table through Spark."""

import pytest

from approxboot import catalog

from .conftest import SF


@pytest.mark.parametrize("name", ["delta_optimal_share", "delta_part_size", "delta_sketch_size", "delta_work_saved"])
def test_orders_are_read(spark, name):
    assert any(f.endswith("/orders.parquet") for f in catalog.QUERIES[name](spark, SF).inputFiles())
