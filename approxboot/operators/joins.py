"""Joins and windows that resampling jobs need and Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def weighted(df: DataFrame, w: Column, aggs: dict[str, tuple[str, str]], by: list[str] | None = None) -> DataFrame:
    """Aggregates {out: (function, column)} of weighted rows: sum, avg, count or median."""
    made = []
    for out, (f, c) in aggs.items():
        x = F.col(c)
        made.append({"sum": F.sum(w * x), "avg": F.sum(w * x) / F.sum(F.when(x.isNotNull(), w)), "count": F.sum(F.when(x.isNotNull(), w)), "median": F.percentile(F.when(w > 0, x), F.lit(0.5), F.greatest(w, F.lit(1)))}[f].alias(out))
    return df.groupBy(*(by or [])).agg(*made)


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str], take: list[str], direction: str = "backward") -> DataFrame:
    """left with the columns take of the last row of right at or before on (or first at or after), for equal by.

    One union, one shuffle, one window. Rows of right at the same time as a left row count as before it.
    """
    l = left.withColumn("_side", F.lit(1)).withColumn("_r", F.lit(None).cast(right.select(F.struct(*take).alias("s")).schema[0].dataType))
    r = right.select(*by, on, F.struct(*take).alias("_r")).withColumn("_side", F.lit(0))
    for c in left.columns:
        if c not in r.columns:
            r = r.withColumn(c, F.lit(None).cast(left.schema[c].dataType))
    both = l.unionByName(r.select(l.columns))
    if direction == "backward":
        w = Window.partitionBy(*by).orderBy(F.col(on), "_side").rowsBetween(Window.unboundedPreceding, 0)
    else:
        w = Window.partitionBy(*by).orderBy(F.col(on).desc(), "_side").rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("_m", F.last("_r", ignorenulls=True).over(w)).where("_side = 1")
    return found.select(*left.columns, *[F.col(f"_m.{c}").alias(f"asof_{c}") for c in take])


def interval_join(left: DataFrame, right: DataFrame, by: list[str], at: Column, lo: Column, hi: Column, bucket: float) -> DataFrame:
    """Pairs with equal by and at (of left, a number) within [lo, hi] of right: an equi-join on buckets of at, instead of a comparison of all."""
    l = left.withColumn("_b", F.floor(at / bucket))
    r = right.withColumn("_b", F.explode(F.sequence(F.floor(lo / bucket), F.floor(hi / bucket))))
    return l.join(r, [*by, "_b"]).where((at >= lo) & (at <= hi)).drop("_b")


def topk_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; tasks cut to k before the shuffle."""
    return df.withColumn("_k", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_k") <= k).drop("_k")
