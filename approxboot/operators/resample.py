"""Resamples as weights: a row's number of draws in each replicate, never the drawn rows themselves."""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations_with_replacement
from math import factorial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from approxboot.functions import rng
from approxboot.functions.statistics import Statistic
from approxboot.sources.shared import ensure_checkpoint


#: Bytes of a table that is worth dealing out: replicated rows at least, and rows at most.
LEAST_SPREAD, MOST_SPREAD = 4 << 20, 1 << 30


def spread(df: DataFrame, ids: list[str], times: int = 1) -> DataFrame:
    """A small df dealt over all cores by its ids, where its scan has fewer tasks than there are cores; others stay where they are.

    Sizes are the optimizer's estimates. times says how often each row is about to be repeated.
    """
    if df.isStreaming:
        return df
    spark = df.sparkSession
    cores = spark.sparkContext.defaultParallelism
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if size * times < LEAST_SPREAD or size >= min(MOST_SPREAD, cores * spark._jsparkSession.sessionState().conf().filesMaxPartitionBytes()):
        return df
    return df.repartition(cores, *ids)


def replicated(df: DataFrame, ids: list[str], replicates: int, seed: int = 0, kind: str = "xx", own: bool = False, dealt: bool = False) -> DataFrame:
    """df once for each replicate b with Poisson(1) weight w; rows of weight 0 are left out. own adds the rows themselves, as replicate -1; dealt: df lies as it should."""
    out = (df if dealt else spread(df, ids, replicates)).withColumn("b", F.explode(F.sequence(F.lit(-1 if own else 0), F.lit(replicates - 1))))
    # as an element of an array the uniform is made once, not again for each comparison of the weight
    out = out.withColumn("_u", F.explode(F.array(rng.uniform(kind, rng.BOOT, *ids, "b", seed=seed))))
    w = rng.poisson_weight(F.col("_u"))
    return out.withColumn("w", F.when(F.col("b") < 0, F.lit(1).cast("long")).otherwise(w) if own else w).where("w > 0").drop("_u")


def bootstrap_states(
    df: DataFrame, stat: Statistic, ids: list[str], replicates: int = 30, by: list[str] | None = None, seed: int = 0, kind: str = "xx", gen: Column | None = None, own: bool = False, dealt: bool = False, weight: str | None = None,
) -> DataFrame:
    """Poisson bootstrap in one plan: states by (by, b), partial in each task, so only states are shuffled.

    own adds the state of the rows themselves, as replicate -1, and the column rows of states' numbers of rows.
    weight names a column of sampling weights, by which rows count.
    """
    by = by or []
    weighted = replicated(df, ids, replicates, seed, kind, own, dealt)
    if gen is not None:
        weighted, by = weighted.withColumn("gen", gen), [*by, "gen"]
    w = F.col("w") * F.col(weight) if weight else F.col("w")
    return weighted.groupBy(*by, "b").agg(*stat.aggs(w), *([F.count(F.lit(1)).alias("rows")] if own else []))


def bootstrap_poisson(df: DataFrame, stat: Statistic, ids: list[str], replicates: int = 30, by: list[str] | None = None, p: float = 1.0, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Result distribution (by, b, theta) of a statistic under the Poisson bootstrap."""
    return stat.answer(bootstrap_states(df, stat, ids, replicates, by, seed, kind), [*(by or []), "b"], p)


def numbered(sample: DataFrame, order: list[Column | str]) -> DataFrame:
    """A sample with positions pos from 0. One task numbers it: for samples of planned size; numbered_table is for tables."""
    return sample.withColumn("pos", F.row_number().over(Window.orderBy(*order)).cast("long") - 1)


def numbered_table(df: DataFrame, order: list[str], out: str = "pos") -> DataFrame:
    """A whole table with positions from 0 in an order without ties: ranges of the order are counted and numbered apart.

    The driver holds a number for each range. df is checkpointed in its ranges, so that both passes see the same.
    """
    spark = df.sparkSession
    ensure_checkpoint(spark)
    fixed = df.repartitionByRange(*order).sortWithinPartitions(*order).checkpoint().withColumn("_m", F.monotonically_increasing_id())
    split = F.shiftright("_m", 33)
    sizes = sorted((r["k"], r["n"]) for r in fixed.groupBy(split.alias("k")).agg(F.count(F.lit(1)).alias("n")).collect())
    ends = np.cumsum([n for _, n in sizes]).tolist()
    before = spark.createDataFrame([(k, e - n) for (k, n), e in zip(sizes, ends)], "_k long, _before long")
    placed = fixed.withColumn("_k", split).join(F.broadcast(before), "_k")
    return placed.withColumn(out, F.col("_before") + F.col("_m").bitwiseAND(F.lit((1 << 33) - 1))).drop("_k", "_before", "_m")


def multinomial_weights(sample: DataFrame, n: int, replicates: int, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Fixed-size resamples: (b, pos, w) with n draws in each replicate; sample has n rows numbered pos."""
    draws = sample.sparkSession.range(replicates * n).select((F.col("id") / n).cast("long").alias("b"), F.pmod("id", F.lit(n)).alias("j"))
    return draws.select("b", rng.draw_index(kind, n, "b", "j", seed=seed).alias("pos")).groupBy("b", "pos").agg(F.count(F.lit(1)).alias("w"))


def bootstrap_multinomial(sample: DataFrame, stat: Statistic, n: int, replicates: int = 30, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Result distribution (b, theta) of fixed-size resamples of a numbered sample."""
    weights = multinomial_weights(sample, n, replicates, seed, kind)
    return stat.answer(sample.join(weights, "pos").groupBy("b").agg(*stat.aggs(F.col("w"))), ["b"])


def bootstrap_multinomial_at_scale(df: DataFrame, x: str, replicates: int = 30, seed: int = 0) -> DataFrame:
    """Fixed-size resamples of a whole distributed sample: (b, n, sx, sxx).

    Each replicate's draws are split over partitions by one multinomial on the driver (replicates x
    partitions numbers), and each partition draws its own part. df must not change between its two passes:
    give it checkpointed or written.
    """
    sizes = {r["k"]: r["n"] for r in df.groupBy(F.spark_partition_id().alias("k")).agg(F.count(F.lit(1)).alias("n")).collect()}
    parts = sorted(sizes)
    quotas = rng.split_draws(sum(sizes.values()), [sizes[k] for k in parts], replicates, seed)
    by_part = {k: quotas[:, i] for i, k in enumerate(parts)}

    def draw(batches):
        from pyspark import TaskContext

        k = TaskContext.get().partitionId()
        held = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
        if not held or not sum(map(len, held)):
            return
        v = np.concatenate(held).astype(float)
        gen = np.random.Generator(np.random.PCG64([seed, k]))
        rows = []
        for b, q in enumerate(by_part[k].tolist()):
            w = np.bincount(gen.integers(0, len(v), q), minlength=len(v))
            rows.append((b, q, float(w @ v), float(w @ (v * v))))
        columns = list(zip(*rows))
        yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2]), pa.array(columns[3])], names=["b", "n", "sx", "sxx"])

    states = df.select(F.col(x).cast("double").alias(x)).mapInArrow(draw, "b long, n long, sx double, sxx double")
    return states.groupBy("b").agg(F.sum("n").alias("n"), F.sum("sx").alias("sx"), F.sum("sxx").alias("sxx"))


def bootstrap_arrow(df: DataFrame, x: str, block: Column, replicates: int = 30, seed: int = 0) -> DataFrame:
    """Poisson bootstrap of moments with weights drawn in arrays: (b, sw, swx, swxx).

    block (a hash bucket of the row id) seeds the weights of its rows together with the places of their task and
    batch, so that no two runs of rows share weights and a retried task over the same rows draws the same. Best
    for many replicates.
    """
    grouped = df.select(F.col(x).cast("double").alias("x"), block.cast("long").alias("k"))

    def draw(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        for number, batch in enumerate(batches):
            xs, ks = batch.column("x").to_numpy(zero_copy_only=False), batch.column("k").to_numpy(zero_copy_only=False)
            out = np.zeros((replicates, 3))
            for k in np.unique(ks):
                v = xs[ks == k]
                w = np.random.Generator(np.random.PCG64([seed, int(k) & 0x7FFFFFFFFFFFFFFF, part, number])).poisson(1.0, (replicates, len(v)))
                out += np.column_stack([w.sum(1), w @ v, w @ (v * v)])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(replicates)), *[pa.array(out[:, i]) for i in range(3)]], names=["b", "sw", "swx", "swxx"])

    states = grouped.mapInArrow(draw, "b long, sw double, swx double, swxx double")
    return states.groupBy("b").agg(*[F.sum(c).alias(c) for c in ("sw", "swx", "swxx")])


def bootstrap_loop(sample: DataFrame, replicates: int, job: Callable[[DataFrame], float], seed: int = 0, ids: list[str] | None = None, kind: str = "xx") -> list[float]:
    """Baseline and last resort: one job for each replicate of any function of a DataFrame. Rows are drawn by the built-in sampler or, with ids, repeated by their Poisson weights."""
    if ids is None:
        return [job(sample.sample(True, 1.0, seed + b)) for b in range(replicates)]

    def repeated(b: int) -> DataFrame:
        w = rng.poisson_weight(rng.uniform(kind, rng.BOOT, *ids, F.lit(b), seed=seed))
        return sample.withColumn("_i", F.explode(F.array_repeat(F.lit(0), w.cast("int")))).drop("_i")

    return [job(repeated(b)) for b in range(replicates)]


def bootstrap_frames(sample: DataFrame, columns: list[str], f: Callable, replicates: int = 30, seed: int = 0, ids: list[str] | None = None, kind: str = "xx") -> DataFrame:
    """(b, theta) of any function of a pandas frame: each replicate's rows, repeated by weight, are one group. For samples, not tables."""
    weighted = replicated(sample, ids or columns, replicates, seed, kind).select("b", "w", *columns)

    def run(pdf):
        import pandas as pd

        rows = pdf.loc[pdf.index.repeat(pdf["w"]), columns]
        return pd.DataFrame({"b": [int(pdf["b"].iloc[0])], "theta": [float(f(rows))]})

    return weighted.groupBy("b").applyInPandas(run, "b long, theta double")


def bootstrap_exact(values: list[float], f: Callable[[np.ndarray], float]) -> tuple[float, float]:
    """Mean and variance of f over all resamples, each with its multinomial probability; 8 values at most."""
    n = len(values)
    if not 1 <= n <= 8:
        raise ValueError("all resamples are enumerated for 1 to 8 values only")
    v = np.asarray(values, float)
    total = mean = square = 0.0
    for pick in combinations_with_replacement(range(n), n):
        ways = factorial(n)
        for c in np.bincount(pick, minlength=n):
            ways //= factorial(int(c))
        theta = f(v[list(pick)])
        total, mean, square = total + ways, mean + ways * theta, square + ways * theta * theta
    return mean / total, square / total - (mean / total) ** 2


def block_weights(blocks: int, replicates: int, spark, seed: int = 0, kind: str = "xx") -> DataFrame:
    """(b, blk, w): draws of whole blocks with replacement, as many as there are."""
    draws = spark.range(replicates * blocks).select((F.col("id") / blocks).cast("long").alias("b"), F.pmod("id", F.lit(blocks)).alias("j"))
    return draws.select("b", rng.draw_index(kind, blocks, "b", "j", seed=seed).alias("blk")).groupBy("b", "blk").agg(F.count(F.lit(1)).alias("w"))


def bootstrap_blocks(df: DataFrame, position: str, n: int, block: int, stat: Statistic, replicates: int = 30, how: str = "fixed", seed: int = 0, kind: str = "xx") -> DataFrame:
    """(b, theta) for dependent rows: runs of block consecutive rows are drawn, so dependence inside them stays.

    fixed: disjoint runs; moving: runs that begin anywhere they fit; circular: anywhere, going on at the start.
    position counts rows from 0 to n - 1 in their order.
    """
    spark = df.sparkSession
    runs = max(1, n // block)
    if how == "fixed":
        weights = block_weights(runs, replicates, spark, seed, kind)
        weighted = df.withColumn("blk", F.floor(F.col(position) / block).cast("long")).join(weights, "blk")
        return stat.answer(weighted.groupBy("b").agg(*stat.aggs(F.col("w"))), ["b"])
    starts = n - block + 1 if how == "moving" else n
    draws = spark.range(replicates * runs).select((F.col("id") / runs).cast("long").alias("b"), F.pmod("id", F.lit(runs)).alias("j"))
    draws = draws.select("b", rng.draw_index(kind, starts, "b", "j", seed=seed).alias("st"))
    # a run is a range of positions: meet it by buckets of block positions, two at most, instead of comparing all
    spread = draws.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("st") / block), F.floor((F.col("st") + block - 1) / block))))
    placed = df.withColumn("_pos", F.col(position))
    if how == "circular":
        placed = placed.unionByName(placed.where(F.col(position) < block).withColumn("_pos", F.col(position) + n))
    placed = placed.withColumn("bucket", F.floor(F.col("_pos") / block))
    met = placed.join(spread, "bucket").where("_pos >= st").where(F.col("_pos") < F.col("st") + block)
    return stat.answer(met.groupBy("b").agg(*stat.aggs(F.lit(1))), ["b"])


def bootstrap_keys(df: DataFrame, stat: Statistic, key: str, replicates: int = 30, seed: int = 0, kind: str = "xx") -> DataFrame:
    """(b, theta) with one weight for all rows of a key: for samples of keys."""
    return bootstrap_poisson(df, stat, [key], replicates, seed=seed, kind=kind)


def jackknife_mean(df: DataFrame, x: str) -> DataFrame:
    """One row (n, theta, se): leave-one-out from totals, each value subtracted once, in one pass over moments."""
    m = df.agg(F.count(x).alias("n"), F.sum(x).alias("s"), F.sum(F.col(x) * F.col(x)).alias("q"))
    # the leave-one-out means are (s - x) / (n - 1): their spread follows from the moments
    spread = (F.col("q") - F.col("s") * F.col("s") / F.col("n")) / ((F.col("n") - 1) * (F.col("n") - 1))
    return m.select("n", (F.col("s") / F.col("n")).alias("theta"), F.sqrt((F.col("n") - 1) / F.col("n") * spread).alias("se"))


def _middle(df: DataFrame, x: str, accuracy: int = 100_000) -> DataFrame:
    """(x, c, last, n): distinct values around the median with their counts and last ranks, and the number of all values.

    A sketch gives bounds on both sides of the middle; rows below are counted, and only values between are sorted.
    """
    v = df.where(F.col(x).isNotNull()).select(F.col(x).alias("x"))
    slack = 4.0 / accuracy
    lo, hi = F.percentile_approx("x", F.lit(0.5 - slack), F.lit(accuracy)), F.percentile_approx("x", F.lit(0.5 + slack), F.lit(accuracy))
    bounds = v.agg(lo.alias("_lo"), hi.alias("_hi"), F.count(F.lit(1)).alias("n"))
    # the middle's ranks must lie within the bounds: of few values all are sorted
    wide = F.col("n") < 3 * accuracy
    placed = v.join(F.broadcast(bounds)).withColumn("_at", F.when(wide, 0).when(F.col("x") < F.col("_lo"), -1).when(F.col("x") > F.col("_hi"), 1).otherwise(0))
    counts = placed.where("_at <= 0").groupBy("n", F.when(F.col("_at") == 0, F.col("x")).alias("x")).agg(F.count(F.lit(1)).alias("c"))
    last = F.sum("c").over(Window.partitionBy("n").orderBy(F.asc_nulls_first("x")).rowsBetween(Window.unboundedPreceding, 0))
    return counts.withColumn("last", last).where("x is not null")


def jackknife_median(df: DataFrame, x: str) -> DataFrame:
    """One row (n, theta, se) for the median: leave-one-out takes three values at most, by where the left-out rank lies.

    The ordinary jackknife, kept as a baseline; its error of a median is not consistent.
    """
    at = lambda k: F.max(F.when((F.col("last") >= k) & (F.col("last") - F.col("c") < k), F.col("x")))
    joined = _middle(df, x)
    half = F.floor(F.col("n") / 2)
    even = joined.where(F.pmod("n", F.lit(2)) == 0).groupBy("n").agg(at(half).alias("a"), at(half + 1).alias("c"))
    odd = joined.where(F.pmod("n", F.lit(2)) == 1).groupBy("n").agg(at(half).alias("a"), at(half + 1).alias("m"), at(half + 2).alias("c"))
    e = even.select("n", ((F.col("a") + F.col("c")) / 2).alias("theta"), (F.col("c") - F.col("a")).alias("_d"))
    e = e.select("n", "theta", F.sqrt((F.col("n") - 1) / F.col("n") * F.col("n") * F.col("_d") * F.col("_d") / 4).alias("se"))
    k = (F.col("n") - 1) / 2
    low, mid, high = (F.col("m") + F.col("c")) / 2, (F.col("a") + F.col("c")) / 2, (F.col("a") + F.col("m")) / 2
    avg = (k * low + mid + k * high) / F.col("n")
    spread = k * (low - avg) ** 2 + (mid - avg) ** 2 + k * (high - avg) ** 2
    o = odd.select("n", F.col("m").alias("theta"), F.sqrt((F.col("n") - 1) / F.col("n") * spread).alias("se"))
    return e.unionByName(o)


def jackknife_groups(df: DataFrame, stat: Statistic, group: Column, groups: int) -> DataFrame:
    """One row (groups, theta, se) of the delete-a-group jackknife: states by group are summed, and each is taken away once."""
    states = df.withColumn("g", group).groupBy("g").agg(*stat.aggs(F.lit(1)))
    total = states.agg(*stat.merge_aggs())
    names = stat.columns()
    left = states.select("g", *[F.col(c).alias(f"_{c}") for c in names]).join(F.broadcast(total))
    thetas = stat.answer(left.select("g", *[(F.col(c) - F.col(f"_{c}")).alias(c) for c in names]), ["g"])
    return thetas.agg(F.count("theta").alias("groups"), F.avg("theta").alias("theta"), F.sqrt((F.count("theta") - 1) * F.var_pop("theta")).alias("se"))


def analytic_se(df: DataFrame, x: str) -> DataFrame:
    """One row (n, mean, se, cv): closed form for the mean."""
    return df.agg(F.count(x).alias("n"), F.avg(x).alias("mean"), F.sqrt(F.var_samp(x) / F.count(x)).alias("se")).withColumn("cv", F.col("se") / F.abs("mean"))
