"""Replayed streams keep their rows out of the driver."""

import pytest

from approxboot import catalog

from .conftest import SF


@pytest.mark.parametrize("name", ["strm_dedup", "strm_dedup_watermark", "strm_session", "strm_static_join"])
def test_appended_rows_lie_in_files(spark, name):
    before = {k: v for k, v in spark.conf.getAll.items() if "stateStore" in k}
    files = catalog.QUERIES[name](spark, SF).inputFiles()
    assert files and all("/replayed-" in f for f in files)
    assert {k: v for k, v in spark.conf.getAll.items() if "stateStore" in k} == before
