"""Statistics as mergeable weighted states.

A statistic names its state columns as aggregates over a value and a weight, says how states merge (sum, min
or max of columns), turns merged states into a result, and rescales results of a sample of fraction p. The
same four phases serve one sample, many replicates, growth by increments and streams.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _identity(result: Column, p: float) -> Column:
    return result


@dataclass(frozen=True)
class Statistic:
    """name; begin(w) gives the state's aggregates; merges says how each state column merges; result of states."""

    name: str
    begin: Callable[[Column], dict[str, Column]]
    result: Callable[[], Column]
    merges: dict[str, str] = field(default_factory=dict)
    rescale: Callable[[Column, float], Column] = _identity
    reliable: bool = True
    invertible: bool = True

    def aggs(self, weight: Column) -> list[Column]:
        return [c.alias(k) for k, c in self.begin(weight).items()]

    def columns(self) -> list[str]:
        return list(self.begin(F.lit(1)))

    def merge_aggs(self) -> list[Column]:
        return [getattr(F, self.merges.get(k, "sum"))(k).alias(k) for k in self.columns()]

    def answer(self, states: DataFrame, by: list[str], p: float = 1.0, out: str = "theta") -> DataFrame:
        return states.select(*by, self.rescale(self.result(), p).alias(out))


def mean(x) -> Statistic:
    x = _c(x)
    return Statistic("mean", lambda w: {"sw": F.sum(F.when(x.isNotNull(), w)), "swx": F.sum(w * x)}, lambda: F.col("swx") / F.nullif(F.col("sw"), F.lit(0)))


def total(x, known_n: int | None = None) -> Statistic:
    """Sum over the population: the sample's sum over p, or N times the mean where N is known."""
    x = _c(x)
    begin = lambda w: {"sw": F.sum(w), "swx": F.sum(w * x)}
    if known_n is not None:
        # as a double: N times a sum of whole numbers can exceed 64 bits
        return Statistic("sum", begin, lambda: F.lit(float(known_n)) * F.col("swx") / F.nullif(F.col("sw"), F.lit(0)))
    return Statistic("sum", begin, lambda: F.col("swx"), rescale=lambda r, p: r / F.lit(p))


def count(condition=None) -> Statistic:
    c = F.lit(True) if condition is None else _c(condition)
    return Statistic("count", lambda w: {"sw": F.sum(F.when(c, w).otherwise(0))}, lambda: F.col("sw"), rescale=lambda r, p: r / F.lit(p))


def proportion(condition) -> Statistic:
    c = _c(condition)
    return Statistic("proportion", lambda w: {"swc": F.sum(F.when(c, w).otherwise(0)), "sw": F.sum(F.when(c.isNotNull(), w))}, lambda: F.col("swc") / F.nullif(F.col("sw"), F.lit(0)))


def variance(x, centre: float = 0.0, root: bool = False) -> Statistic:
    """Population variance (or deviation) of x from moments about centre."""
    x = _c(x) - F.lit(centre)

    def result():
        m = F.col("swx") / F.nullif(F.col("sw"), F.lit(0))
        v = F.col("swx2") / F.nullif(F.col("sw"), F.lit(0)) - m * m
        return F.sqrt(F.greatest(v, F.lit(0.0))) if root else v

    return Statistic("stddev" if root else "variance", lambda w: {"sw": F.sum(F.when(x.isNotNull(), w)), "swx": F.sum(w * x), "swx2": F.sum(w * x * x)}, result)


def ratio(x, y) -> Statistic:
    x, y = _c(x), _c(y)
    return Statistic("ratio", lambda w: {"swx": F.sum(w * x), "swy": F.sum(w * y)}, lambda: F.col("swx") / F.nullif(F.col("swy"), F.lit(0)))


def _cross(x: Column, y: Column):
    return lambda w: {"sw": F.sum(w), "swx": F.sum(w * x), "swy": F.sum(w * y), "swxx": F.sum(w * x * x), "swyy": F.sum(w * y * y), "swxy": F.sum(w * x * y)}


def covariance(x, y) -> Statistic:
    return Statistic("covariance", _cross(_c(x), _c(y)), lambda: F.col("swxy") / F.col("sw") - F.col("swx") * F.col("swy") / F.col("sw") / F.col("sw"))


def correlation(x, y) -> Statistic:
    def result():
        n = F.col("sw")
        top = n * F.col("swxy") - F.col("swx") * F.col("swy")
        return top / F.sqrt((n * F.col("swxx") - F.col("swx") * F.col("swx")) * (n * F.col("swyy") - F.col("swy") * F.col("swy")))

    return Statistic("correlation", _cross(_c(x), _c(y)), result)


def slope(x, y) -> Statistic:
    """Slope of the least-squares line of y on x."""
    return Statistic("slope", _cross(_c(x), _c(y)), lambda: (F.col("sw") * F.col("swxy") - F.col("swx") * F.col("swy")) / (F.col("sw") * F.col("swxx") - F.col("swx") * F.col("swx")))


def minimum(x) -> Statistic:
    x = _c(x)
    return Statistic("min", lambda w: {"m": F.min(F.when(w > 0, x))}, lambda: F.col("m"), {"m": "min"}, reliable=False, invertible=False)


def maximum(x) -> Statistic:
    x = _c(x)
    return Statistic("max", lambda w: {"m": F.max(F.when(w > 0, x))}, lambda: F.col("m"), {"m": "max"}, reliable=False, invertible=False)


def quantile(x, q: float = 0.5) -> Statistic:
    """Exact weighted quantile; its state is the values themselves, so it does not merge: for samples."""
    x = _c(x)
    return Statistic("quantile", lambda w: {"m": F.percentile(F.when(w > 0, x), F.lit(q), F.greatest(w, F.lit(1)))}, lambda: F.col("m"), {"m": "none"}, invertible=False)


def quantile_sketch(x, q: float = 0.5) -> Statistic:
    """Quantile by KLL sketches over weighted rows, which merge: for samples beyond memory."""
    x = _c(x).cast("double")
    return Statistic("quantile_sketch", lambda w: {"m": F.kll_sketch_agg_double(F.when(w > 0, x))}, lambda: F.kll_sketch_get_quantile_double(F.col("m"), F.lit(q)), {"m": "kll_sketch_merge_double"}, invertible=False)


def distinct(x) -> Statistic:
    """Distinct values by a mergeable sketch. A sample's count is not the population's: flagged."""
    x = _c(x)
    return Statistic("distinct", lambda w: {"m": F.hll_sketch_agg(F.when(w > 0, x))}, lambda: F.hll_sketch_estimate("m"), {"m": "hll_union_agg"}, reliable=False, invertible=False)


def linear_model(xs: list[str], y: str):
    """Multiple linear regression as sums of products: (aggregates of weight, solver of one state row)."""
    names = ["_one", *xs]
    col = {n: (F.lit(1.0) if n == "_one" else F.col(n)) for n in names}

    def aggs(w: Column) -> list[Column]:
        out = [F.sum(w * col[a] * col[b]).alias(f"xx_{i}_{j}") for i, a in enumerate(names) for j, b in enumerate(names) if i <= j]
        return out + [F.sum(w * col[a] * F.col(y)).alias(f"xy_{i}") for i, a in enumerate(names)]

    def solve(row) -> np.ndarray:
        k = len(names)
        m = np.array([[row[f"xx_{min(i, j)}_{max(i, j)}"] for j in range(k)] for i in range(k)], float)
        return np.linalg.solve(m, np.array([row[f"xy_{i}"] for i in range(k)], float))

    return aggs, solve
