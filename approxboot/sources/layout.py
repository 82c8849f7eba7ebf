"""A pre-hashed layout: rows in buckets by their sampling uniform, so that a sample is a partition filter."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.functions import rng


def write_shuffled(df: DataFrame, path: str, ids: list[str], buckets: int = 100, seed: int = 0, kind: str = "xx") -> None:
    """Write df partitioned by bucket = floor(u * buckets), one shuffle, once; any prefix of buckets is a uniform sample."""
    u = rng.uniform(kind, rng.SAMPLE, *ids, seed=seed)
    out = df.withColumn("u", u).withColumn("bucket", F.floor(F.col("u") * buckets).cast("int"))
    out.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)
    # rows and bytes of each bucket, beside the table: what a sample will read is known before it is read
    written = spark_table(df.sparkSession, path)
    files = written.groupBy("bucket", "_metadata.file_path", "_metadata.file_size").agg(F.count(F.lit(1)).alias("n"))
    sizes = files.groupBy("bucket").agg(F.sum("n").alias("rows"), F.sum("file_size").alias("bytes"))
    sizes.coalesce(1).write.mode("overwrite").parquet(f"{path}.sizes")


def spark_table(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def sizes(spark: SparkSession, path: str) -> dict[int, tuple[int, int]]:
    """(rows, bytes) of each bucket, by the small table beside the layout."""
    return {r["bucket"]: (r["rows"], r["bytes"]) for r in spark.read.parquet(f"{path}.sizes").collect()}


def read_fraction(spark: SparkSession, path: str, p: float, buckets: int = 100, low: float = 0.0) -> DataFrame:
    """Rows of [low, p): whole buckets are pruned by the partition filter, the edge buckets by u."""
    df = spark_table(spark, path)
    inside = (F.col("bucket") < math.ceil(p * buckets)) & (F.col("bucket") >= math.floor(low * buckets))
    return df.where(inside).where((F.col("u") < p) & (F.col("u") >= low))
