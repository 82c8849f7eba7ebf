"""The early-answer loop: pilot, plan, sample, resample in one Spark plan, test the error, grow or stop."""

from __future__ import annotations

import datetime as dt
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from approxboot.functions import accuracy
from approxboot.functions.statistics import Statistic
from approxboot.operators.maintain import merge_states
from approxboot.operators.resample import bootstrap_states, spread
from approxboot.operators.sampling import SampleCursor
from approxboot.plans import planner
from approxboot.sources.sampled import PILOT_ROWS, ScanSource
from approxboot.sources.shared import ensure_checkpoint


@dataclass
class Answer:
    """rows: a DataFrame of one row per group (value, cv, variance, lo, hi, ...); error over groups; how it came about; rows and bytes read."""

    rows: DataFrame
    error: float | None
    mode: str
    n: int
    B: int
    p: float
    iterations: int
    message: str
    log: list[dict] = field(default_factory=list)
    read: dict = field(default_factory=dict)


class ErrorLog:
    """Error records with time stamps; read() gives those newer than the last read, averaged."""

    def __init__(self):
        self.rows: list[dict] = []
        self._read = 0

    def add(self, iteration: int, error: float | None) -> None:
        self.rows.append({"iteration": iteration, "error": error, "at": dt.datetime.now(dt.timezone.utc)})

    def read(self) -> float | None:
        new = [r["error"] for r in self.rows[self._read :] if r["error"] is not None]
        self._read = len(self.rows)
        return sum(new) / len(new) if new else None


def pilot_values(df: DataFrame, x: str, ids: list[str], p: float, seed: int, kind: str = "xx") -> np.ndarray:
    """Values of a pilot sample in the order of their uniforms, so that its prefixes are samples too."""
    cursor = SampleCursor(df, ids, seed, kind)
    rows = cursor.grow(p).select(F.col(x).cast("double").alias("x"), cursor.u().alias("u")).where("x is not null").orderBy("u").limit(PILOT_ROWS)
    return np.array([r["x"] for r in rows.collect()])


def fixed_plan(df: DataFrame, stat: Statistic, ids: list[str], p: float, B: int = 30, by: list[str] | None = None, level: float = 0.95, seed: int = 0, kind: str = "xx") -> DataFrame:
    """One round with p and B given: (by, value, cv, variance, lo, hi, pct_lo, pct_hi, replicates, n, p). A group that the sample misses has no row."""
    by = by or []
    # md5 is dear enough that a small table is dealt out before it is sampled
    dealt = kind == "md5"
    sample = SampleCursor(spread(df, ids) if dealt else df, ids, seed, kind).grow(p)
    states = bootstrap_states(sample, stat, ids, B, by, seed, kind, own=True, dealt=dealt)
    thetas = stat.answer(states, [*by, "b", "rows"], p).withColumn("theta", F.when(F.col("b") >= 0, F.col("theta")))
    n = F.coalesce(F.max(F.when(F.col("b") < 0, F.col("rows"))), F.lit(0)).cast("long")
    return accuracy.summarise(thetas, by, level=level, more=[n.alias("n")]).withColumn("p", F.lit(p))


def exact(df: DataFrame, stat: Statistic, by: list[str] | None = None) -> DataFrame:
    """Baseline and fallback: the plain aggregate over all rows."""
    by = by or []
    return stat.answer(df.groupBy(*by).agg(*stat.aggs(F.lit(1))), by, 1.0, "value")


def early_result(
    df, stat: Statistic, x: str, ids: list[str] | None, sigma: float, tau: float = 0.01, by: list[str] | None = None, N: int | None = None, local=np.mean, p_pilot: float = 0.01, combine: str = "avg", level: float = 0.95,
    confidence: float | None = None, max_iterations: int = 5, fixed: tuple[int, int] | None = None, seed: int = 0, kind: str = "xx", whole: DataFrame | None = None, least_bytes: int = 0,
) -> Answer:
    """Answer stat over df with an error of sigma at most, early where that pays.

    df is a table, or a source of samples (approxboot.sources.sampled) that reads less than all of it; then whole
    is the table for the exact run. x is the column whose pilot values plan the run through local, the statistic
    as a function of an array. Growth reads only new rows: their states are merged into those so far. fixed gives
    (B, n) instead of a plan. A table that the optimizer takes to be smaller than least_bytes is answered exactly
    at once: a pilot would cost as much.
    """
    by = by or []
    source = df if hasattr(df, "grow") else ScanSource(df, ids, seed, kind, N)
    whole, ids = whole if whole is not None else getattr(source, "df", None), source.ids
    if whole is not None and least_bytes and (size := int(whole._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) < least_bytes:
        return _exact_answer(whole, stat, by, f"a table of {size} bytes is answered exactly", source.read)
    N = source.count()
    if fixed:
        B, n = fixed
        ok, message = planner.feasible(B, n, N)
        made = planner.Plan(B, n, min(1.0, n / max(1, N)), "early" if ok else "exact", message)
    else:
        share = min(1.0, max(p_pilot, 2 / tau / max(1, N)), PILOT_ROWS / max(1, N))
        values = source.pilot(share).select(F.col(x).cast("double").alias("x")).where("x is not null").collect()
        made = planner.plan(np.array([r["x"] for r in values]), local, N, sigma, tau, confidence, seed=seed)
    if made.mode == "exact" and whole is not None:
        return _exact_answer(whole, stat, by, made.message, source.read, N)
    z = accuracy.z_value(confidence) if confidence else 1.0
    log, states, p, B = ErrorLog(), None, made.p, made.B or 30
    for i in range(1, max_iterations + 1):
        fresh = bootstrap_states(source.grow(p), stat, ids, B, by, seed, kind, weight=source.weight)
        # states are replicates x groups rows; cutting their lineage keeps each round's plan short
        states = _kept(fresh if states is None else merge_states(states, fresh, stat, [*by, "b"]))
        rows = accuracy.summarise(stat.answer(states, [*by, "b"], p), by, level=level)
        error = accuracy.combine_errors(rows, how=combine).first()["error"]
        log.add(i, error)
        if error is not None and z * error <= sigma or p >= 1:
            break
        # the error falls with the root of n: go there at once, a little beyond
        p = min(1.0, max(p * 1.5, p * 1.1 * (z * (error or 2 * sigma) / sigma) ** 2))
    return Answer(rows, error, "early", int(round(p * N)), B, p, i, made.message, log.rows, source.read)


def _exact_answer(whole: DataFrame, stat: Statistic, by: list[str], message: str, read: dict, n: int = 0) -> Answer:
    rows = exact(whole, stat, by).select(*by, "value", F.lit(0.0).alias("cv"), F.lit(0.0).alias("variance"), F.col("value").alias("lo"), F.col("value").alias("hi"))
    return Answer(rows, 0.0, "exact", n, 0, 1.0, 0, message, read=read)


def _kept(df: DataFrame) -> DataFrame:
    ensure_checkpoint(df.sparkSession)
    return df.checkpoint()


def estimate_with_losses(df: DataFrame, split, lost, stat: Statistic, ids: list[str], splits: int, n_lost: int, sigma: float, B: int = 30, seed: int = 0, kind: str = "xx") -> DataFrame:
    """One row (value, cv, ..., p_eff, accepted) from the splits that survive: an answer instead of a restart. Right if loss is independent of values."""
    p_eff = 1 - n_lost / splits
    left = df.withColumn("split", split).where(~lost)
    thetas = stat.answer(bootstrap_states(left, stat, ids, B, None, seed, kind), ["b"], p_eff)
    out = accuracy.summarise(thetas)
    return out.withColumn("p_eff", F.lit(p_eff)).withColumn("accepted", F.col("cv") <= sigma)


def estimates_with_losses(df: DataFrame, split, cases: list[tuple[int, object, int]], stat: Statistic, ids: list[str], splits: int, sigma: float, B: int = 30, seed: int = 0, kind: str = "xx") -> DataFrame:
    """The same for several losses (label, lost, n_lost) at once, one row each with its label in case: states by split are made once, and each case merges those of the splits that it keeps."""
    states = bootstrap_states(df.withColumn("split", split), stat, ids, B, ["split"], seed, kind)
    kept = F.filter(F.array(*[F.when(~lost, F.lit(label)) for label, lost, _ in cases]), lambda c: c.isNotNull())
    merged = states.withColumn("case", F.explode(kept)).groupBy("case", "b").agg(*stat.merge_aggs())
    share = F.coalesce(*[F.when(F.col("case") == label, F.lit(1 - n / splits)) for label, _, n in cases])
    thetas = merged.select("case", share.alias("p_eff"), stat.rescale(stat.result(), share).alias("theta"))
    return accuracy.summarise(thetas, ["case", "p_eff"]).withColumn("accepted", F.col("cv") <= sigma)
