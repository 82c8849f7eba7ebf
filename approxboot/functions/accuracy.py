"""Accuracy measures over result distributions: DataFrames of replicates with the value theta."""

from __future__ import annotations

import math
from itertools import permutations
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def z_value(level: float) -> float:
    return NormalDist().inv_cdf(0.5 + level / 2)


def cv(theta: str = "theta") -> Column:
    """Coefficient of variation; null where the mean is zero: use the variance there."""
    m = F.avg(theta)
    return F.when(m != 0, F.stddev_pop(theta) / F.abs(m))


def boot_variance(theta: str = "theta") -> Column:
    """Variance over replicates, with their number as the divisor."""
    return F.var_pop(theta)


def bias(theta: str, at_sample) -> Column:
    return F.avg(theta) - at_sample


def summarise(dist: DataFrame, by: list[str] | None = None, theta: str = "theta", level: float = 0.95, fpc_p: float | None = None, more: list[Column] | None = None) -> DataFrame:
    """value, cv, variance and normal and percentile bounds by group, and more aggregates. fpc_p: the sample's fraction, for the finite-population correction."""
    tail = (1 - level) / 2
    shrink = F.lit(math.sqrt(1 - fpc_p) if fpc_p else 1.0)
    m, s = F.avg(theta), F.stddev_pop(theta) * shrink
    z = F.lit(z_value(level))
    return dist.groupBy(*(by or [])).agg(
        m.alias("value"), (cv(theta) * shrink).alias("cv"), (F.var_pop(theta) * shrink * shrink).alias("variance"), (m - z * s).alias("lo"), (m + z * s).alias("hi"),
        F.percentile(theta, F.lit(tail)).alias("pct_lo"), F.percentile(theta, F.lit(1 - tail)).alias("pct_hi"), F.count(theta).alias("replicates"), *(more or []),
    )


def ci(values: np.ndarray, at_sample: float, level: float = 0.95, kind: str = "normal") -> tuple[float, float]:
    """Interval from replicates: normal, percentile, or basic (quantiles reflected at the sample's value)."""
    v = np.asarray(values, float)
    if kind == "normal":
        half = z_value(level) * v.std()
        return float(v.mean() - half), float(v.mean() + half)
    lo, hi = np.quantile(v, [(1 - level) / 2, (1 + level) / 2])
    if kind == "percentile":
        return float(lo), float(hi)
    if kind == "basic":
        return float(2 * at_sample - hi), float(2 * at_sample - lo)
    raise ValueError(f"no interval of kind {kind}")


def prop_ci(x: int, n: int, level: float = 0.95) -> tuple[float, float]:
    p = x / n
    half = z_value(level) * math.sqrt(p * (1 - p) / n)
    return p - half, p + half


def prop_ztest(x: int, n: int, p0: float) -> tuple[float, float]:
    """z and two-sided p-value of a share of x in n against p0."""
    z = (x / n - p0) / math.sqrt(p0 * (1 - p0) / n)
    return z, 2 * (1 - NormalDist().cdf(abs(z)))


def stability(cvs: list[float]) -> list[float]:
    """Absolute differences of successive error estimates."""
    return [abs(b - a) for a, b in zip(cvs, cvs[1:])]


def combine_errors(errors: DataFrame, error: str = "cv", how: str = "avg") -> DataFrame:
    """One error of many groups: their average, maximum or 95 % point. Groups without an error count by n_missing."""
    agg = {"avg": F.avg(error), "max": F.max(error), "p95": F.percentile(error, F.lit(0.95))}[how]
    return errors.agg(agg.alias("error"), F.sum(F.col(error).isNull().cast("int")).alias("n_missing"))


def rel_error(estimate: Column, truth: Column) -> Column:
    return F.abs(estimate - truth) / F.abs(F.nullif(truth, F.lit(0)))


def count_error(estimate: float, n: int) -> float:
    """Relative error of a sampler's estimate of the number of pairs."""
    return abs(estimate - n) / n


def coverage(runs: list[dict], truth: float, sigma: float) -> dict:
    """Share of runs (value, lo, hi) whose interval holds truth, and whose relative error is at most sigma."""
    k = len(runs)
    return {"runs": k, "covered": sum(r["lo"] <= truth <= r["hi"] for r in runs) / k, "within": sum(abs(r["value"] - truth) <= sigma * abs(truth) for r in runs) / k}


def centroid_error(found: np.ndarray, best: np.ndarray) -> float:
    """Mean distance of matched centroids over the mean norm of the best; matched by brute force up to 8, else greedily."""
    d = np.linalg.norm(found[:, None] - best[None], axis=2)
    k = len(best)
    if k <= 8:
        cost = min(sum(d[i, j] for i, j in enumerate(p)) for p in permutations(range(k)))
    else:
        cost, left = 0.0, set(range(k))
        for i in range(k):
            j = min(left, key=lambda j: d[i, j])
            cost += d[i, j]
            left.discard(j)
    return float(cost / k / np.linalg.norm(best, axis=1).mean())


def uniformity(blocks: DataFrame, n: str = "n", total: str = "total") -> DataFrame:
    """Chi-square of a sample's counts n by block against the blocks' shares of total, with its degrees of freedom."""
    # one row of sums
    sums = blocks.agg(F.sum(n).alias("_n"), F.sum(total).alias("_t"))
    expected = F.col(total) * F.col("_n") / F.col("_t")
    with_e = blocks.join(F.broadcast(sums)).withColumn("_e", expected)
    return with_e.agg(F.sum((F.col(n) - F.col("_e")) ** 2 / F.col("_e")).alias("chi2"), (F.count(F.lit(1)) - 1).alias("df"))
