"""What the early answers are compared with: progressive answers without errors, online aggregation, separate jobs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from approxboot.functions import rng
from approxboot.functions.accuracy import z_value


def progressive(df: DataFrame, x: str, ids: list[str], steps: list[float], seed: int = 0, kind: str = "xx") -> DataFrame:
    """(p, n, mean): running answers of growing samples, without an error. One pass: rows are counted where they enter."""
    return _running(df, x, ids, steps, seed, kind).select("p", "n", (F.col("s") / F.col("n")).alias("mean"))


def _running(df, x, ids, steps, seed, kind):
    entry = None
    u = rng.uniform(kind, rng.SAMPLE, *ids, seed=seed)
    for p in sorted(steps):
        entry = F.when(F.col("_u") < p, F.lit(p)) if entry is None else entry.when(F.col("_u") < p, F.lit(p))
    # as many rows as steps
    rows = df.select(F.col(x).alias("x"), u.alias("_u")).withColumn("p", entry).where("p is not null")
    parts = rows.groupBy("p").agg(F.count("x").alias("n"), F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("q"))
    w = Window.orderBy("p").rowsBetween(Window.unboundedPreceding, 0)
    return parts.select("p", *[F.sum(c).over(w).alias(c) for c in ("n", "s", "q")])


def online_mean(df: DataFrame, x: str, ids: list[str], steps: list[float], level: float = 0.95, seed: int = 0, kind: str = "xx") -> DataFrame:
    """(p, n, mean, lo, hi): running means with closed-form intervals."""
    r = _running(df, x, ids, steps, seed, kind).withColumn("mean", F.col("s") / F.col("n"))
    half = F.lit(z_value(level)) * F.sqrt((F.col("q") - F.col("n") * F.col("mean") * F.col("mean")) / (F.col("n") - 1) / F.col("n"))
    return r.select("p", "n", "mean", (F.col("mean") - half).alias("lo"), (F.col("mean") + half).alias("hi"))


def cached_sample(sample: DataFrame) -> DataFrame:
    """A sample held for iterative jobs, on the executors' disks."""
    from pyspark import StorageLevel

    return sample.persist(StorageLevel.DISK_ONLY)


def separate_jobs(df: DataFrame, ids: list[str], p: float, replicates: int, job, path: str, seed: int = 0, kind: str = "xx"):
    """The stock way of early answers: one job writes a sample to path, each resample is a job that reads it, the last job is the accuracy. (its row, jobs)."""
    from approxboot.functions.accuracy import summarise
    from approxboot.operators.resample import bootstrap_loop
    from approxboot.operators.sampling import bernoulli

    spark = df.sparkSession
    bernoulli(df, ids, p, seed, kind).write.parquet(path)
    got = bootstrap_loop(spark.read.parquet(path), replicates, job, seed, ids, kind)
    return summarise(spark.createDataFrame([(float(v),) for v in got], "theta double")).first(), replicates + 2
