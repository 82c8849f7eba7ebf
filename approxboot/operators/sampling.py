"""Uniform samples of DataFrames.

Every sample is a filter on a per-row uniform, so samples are nested, grow without an anti-join and are the
same whatever the partitioning. Project to the columns that are needed first: sampling keeps what it is given.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from approxboot.functions import rng


@dataclass
class SampleCursor:
    """A growing sample: rows with uniform below p. grow(p) returns only what is new."""

    df: DataFrame
    ids: list[str]
    seed: int = 0
    kind: str = "xx"
    p: float = 0.0
    steps: list[tuple[float, float]] = field(default_factory=list)

    def u(self) -> Column:
        return rng.uniform(self.kind, rng.SAMPLE, *self.ids, seed=self.seed)

    def grow(self, p: float) -> DataFrame:
        """Rows of [the fraction so far, p)."""
        if not self.p <= p <= 1:
            raise ValueError(f"a sample of {self.p} can't grow to {p}")
        low, self.p = self.p, p
        self.steps.append((low, p))
        u = self.u()
        return self.df.where((u >= low) & (u < p))

    def sample(self) -> DataFrame:
        """All rows so far."""
        return self.df.where(self.u() < self.p)


def bernoulli(df: DataFrame, ids: list[str], p: float, seed: int = 0, kind: str = "xx") -> DataFrame:
    return df.where(rng.uniform(kind, rng.SAMPLE, *ids, seed=seed) < p)


def exact_n(df: DataFrame, ids: list[str], n: int, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Exactly n rows (all, if there are fewer): those of the least uniforms. Each task keeps n rows at most."""
    u = rng.uniform(kind, rng.SAMPLE, *ids, seed=seed)
    return df.withColumn("_u", u).orderBy("_u", *ids).limit(n).drop("_u")


def sample_pairs(df: DataFrame, ids: list[str], n: int | None = None, p: float | None = None, by: list[str] | None = None, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Pairs after parsing: n or fraction p of them, over all or in each group of by; a per-group n keeps only n rows of a task's group."""
    u = rng.uniform(kind, rng.SAMPLE, *ids, seed=seed)
    if p is not None:
        return df.where(u < p)
    if not by:
        return exact_n(df, ids, n, seed, kind)
    rank = F.row_number().over(Window.partitionBy(*by).orderBy("_u", *ids))
    return df.withColumn("_u", u).withColumn("_k", rank).where(F.col("_k") <= n).drop("_u", "_k")


def counted(df: DataFrame, name: str = "pairs"):
    """df and an observation of its exact number of rows, made in the same pass that reads it."""
    from pyspark.sql import Observation

    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("n")), seen


def sample_keys(df: DataFrame, key: str, p: float, seed: int = 0, kind: str = "xx") -> DataFrame:
    """All rows of a fraction p of keys: a cluster sample; resample it by key."""
    return df.where(rng.uniform(kind, rng.SAMPLE, key, seed=seed) < p)


def stratified(df: DataFrame, ids: list[str], column: str, fractions: dict, others: float = 0.0, seed: int = 0, kind: str = "xx") -> DataFrame:
    """A fraction of each stratum; of strata that fractions lacks, nulls among them, the fraction others."""
    p = F.lit(float(others))
    if fractions:
        p = F.coalesce(F.create_map(*[x for k, v in fractions.items() for x in (F.lit(k), F.lit(float(v)))])[F.col(column)], p)
    return df.where(rng.uniform(kind, rng.SAMPLE, *ids, seed=seed) < p)


def blocks_of(df: DataFrame, position: Column | str, block_rows: int) -> DataFrame:
    """df with blk: logical blocks of block_rows rows by a row's position, which doesn't change with partitioning."""
    return df.withColumn("blk", F.floor((F.col(position) if isinstance(position, str) else position) / block_rows).cast("long"))


def sample_blocks(df: DataFrame, position, block_rows: int, p: float, seed: int = 0, kind: str = "xx") -> DataFrame:
    """Baseline: all rows of random blocks. Biased in error, not in mean, where blocks are clustered."""
    return blocks_of(df, position, block_rows).where(rng.uniform(kind, rng.BLOCK, "blk", seed=seed) < p)


def reservoir(df: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """Baseline: exactly n rows over a full scan. Each task holds n rows with random priorities; the n least of all stay."""

    def hold(batches):
        kept = None
        gen = None
        for pdf in batches:
            if gen is None:
                from pyspark import TaskContext

                gen = np.random.Generator(np.random.PCG64([seed, TaskContext.get().partitionId()]))
            pdf = pdf.assign(_r=gen.random(len(pdf)))
            kept = pdf if kept is None else pd.concat([kept, pdf])
            kept = kept.nsmallest(n, "_r")
        if kept is not None:
            yield kept

    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema] + ["_r double"])
    return df.mapInPandas(hold, schema).orderBy("_r").limit(n).drop("_r")


def surviving(df: DataFrame, split: Column, lost: Column) -> DataFrame:
    """Rows of logical splits that were not lost: a sample, if loss does not depend on values."""
    return df.withColumn("split", split).where(~lost)


def choose_sampler(needs_exact_count: bool, n: int, load_critical: bool, small: int = 1000) -> str:
    """lines: sample before loading; pairs: after parsing, when an exact count of pairs matters and loading does not, or the sample is small."""
    if needs_exact_count and not load_critical:
        return "pairs"
    return "pairs" if n < small and not load_critical else "lines"


def explode_pairs(df: DataFrame, expression: Column, out: str = "value") -> DataFrame:
    """A variable number of pairs from each row."""
    return df.select("*", F.posexplode(expression).alias("pos", out))


def word_count_by_lines(docs: DataFrame, p: float, seed: int = 0, kind: str = "xx") -> DataFrame:
    """One row (p, n_est, n_exact, error): words estimated from sampled documents over p, against all."""
    words = F.size(F.filter(F.split("text", " "), lambda w: w != "")).cast("long")
    inside = rng.uniform(kind, rng.SAMPLE, "doc_id", seed=seed) < p
    agg = docs.select(words.alias("w"), inside.alias("i")).agg(F.sum(F.when(F.col("i"), F.col("w")).otherwise(0)).alias("s"), F.sum("w").alias("n_exact"))
    est = F.col("s") / F.lit(p)
    return agg.select(F.lit(p).alias("p"), est.alias("n_est"), "n_exact", (F.abs(est - F.col("n_exact")) / F.col("n_exact")).alias("error"))
