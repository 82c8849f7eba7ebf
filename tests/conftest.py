"""One Spark session for all tests, and a comparison with DuckDB."""

import os

import pytest
from pyspark.sql import SparkSession

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    s = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "4g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.checkpoint.dir", str(tmp_path_factory.mktemp("shared"))).getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    from approxboot import ship_package

    ship_package(s)
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"create view {f.split('.')[0]} as select * from read_parquet('{SF}/{f}')")
    return c


def rows_of(df):
    """Rows as sorted lists of text, columns in order of name; nulls and NaN alike."""
    import pandas as pd

    df = df[sorted(df.columns)]
    out = []
    for r in df.itertuples(index=False):
        out.append([None if x is None or x is pd.NaT or x != x else str(float(x)) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(pd.Timestamp(x)) if hasattr(x, "isoformat") else str(x) for x in r])
    return sorted(out, key=str)
