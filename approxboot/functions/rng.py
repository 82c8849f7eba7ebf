"""Counter-based randomness: every number is a function of seed, salt, row id and replicate.

The portable generator gives the same digits in Spark and in any SQL engine with md5; the fast one is for
production. Sampling and resampling use different salts, so weights do not depend on inclusion.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SAMPLE, BOOT, DRAW, BLOCK = "sample", "boot", "draw", "block"


def poisson_cdf(rate: float = 1.0, most: int = 8) -> list[float]:
    """P(X <= k) for k = 0 ... most - 1."""
    out, term, total = [], math.exp(-rate), 0.0
    for k in range(most):
        total += term
        out.append(total)
        term *= rate / (k + 1)
    return out


def uniform_md5(salt: str, *ids, seed: int = 0) -> Column:
    """Portable uniform in [0, 1): 48 bits of the md5 of salt, seed and ids."""
    parts = [F.lit(f"{salt}|{seed}"), *[F.col(i) if isinstance(i, str) else i for i in ids]]
    digest = F.md5(F.concat_ws("|", *[p.cast("string") for p in parts]))
    return F.conv(F.substring(digest, 1, 12), 16, 10).cast("bigint") / F.lit(float(1 << 48))


def uniform_xx(salt: str, *ids, seed: int = 0) -> Column:
    """Fast uniform in [0, 1): 52 bits of xxhash64."""
    parts = [F.col(i) if isinstance(i, str) else i for i in ids]
    return F.pmod(F.xxhash64(F.lit(f"{salt}|{seed}"), *parts), F.lit(1 << 52)) / F.lit(float(1 << 52))


def uniform(kind: str, salt: str, *ids, seed: int = 0) -> Column:
    return {"md5": uniform_md5, "xx": uniform_xx}[kind](salt, *ids, seed=seed)


def poisson_weight(u: Column) -> Column:
    """Poisson(1) weight of a uniform, by the inverse distribution function."""
    out = None
    for k, c in enumerate(poisson_cdf()):
        out = F.when(u < c, F.lit(k)) if out is None else out.when(u < c, F.lit(k))
    return out.otherwise(F.lit(8)).cast("long")


def draw_index(kind: str, n: int, *ids, seed: int = 0) -> Column:
    """Position in 0 ... n - 1 of a draw with replacement."""
    return F.floor(uniform(kind, DRAW, *ids, seed=seed) * F.lit(n)).cast("long")


def sql_uniform(salt: str, *ids: str, seed: int = 0) -> str:
    """The portable uniform as SQL."""
    parts = ", ".join([f"'{salt}|{seed}'", *[f"cast({i} as varchar)" for i in ids]])
    return f"(cast(concat('0x', substr(md5(concat_ws('|', {parts})), 1, 12)) as bigint) / 281474976710656.0)"


def sql_poisson(u: str) -> str:
    """The Poisson weight of a uniform as SQL."""
    cases = " ".join(f"when {u} < {c!r} then {k}" for k, c in enumerate(poisson_cdf()))
    return f"cast(case {cases} else 8 end as bigint)"


def part_size(n: int, n2: int, seed: int, b: int, mode: str = "binomial") -> int:
    """Items of a resample of size n2 that come from a part of n of n2 items: binomial, or its Gaussian approximation, within 0 ... n2."""
    rng = np.random.Generator(np.random.PCG64([seed, b, n, n2]))
    if n2 <= 0:
        return 0
    if mode == "binomial":
        return int(rng.binomial(n2, n / n2))
    return int(min(n2, max(0, round(rng.normal(n, math.sqrt(n * (1 - n / n2)))))))


def split_draws(n: int, part_sizes: list[int], replicates: int, seed: int) -> np.ndarray:
    """Draws that each replicate of n draws takes from each part: multinomial, replicates x parts."""
    sizes = np.asarray(part_sizes, float)
    if n == 0 or sizes.sum() == 0:
        return np.zeros((replicates, len(sizes)), np.int64)
    rng = np.random.Generator(np.random.PCG64(seed))
    return rng.multinomial(n, sizes / sizes.sum(), size=replicates)
