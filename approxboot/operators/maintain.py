"""Keeping resamples when a sample grows from n to n2 rows.

Poisson weights make maintenance additive: old rows keep their weights and only new rows are read. For
fixed-size resamples, the share that comes from the old part changes by a binomial number of items, which
are deleted or added through random subsets held in memory; a disk layer is touched only when they run out.
"""

from __future__ import annotations

import math
import os
import uuid
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from approxboot.functions import rng
from approxboot.functions.statistics import Statistic


def merge_states(old: DataFrame, new: DataFrame, stat: Statistic, by: list[str]) -> DataFrame:
    """States of the grown sample: those of old and of what is new, merged; old rows are not read again."""
    return old.unionByName(new).groupBy(*by).agg(*stat.merge_aggs())


def maintain_plain(resample: np.ndarray, sample: np.ndarray, delta: np.ndarray, seed: int, b: int = 0, mode: str = "binomial") -> tuple[np.ndarray, int]:
    """A resample of sample and delta together, made from one of sample; and the number of items touched.

    The old part's new size is drawn; items are deleted from it or drawn from sample to match; the rest is
    drawn from delta.
    """
    n, n2 = len(sample), len(sample) + len(delta)
    gen = np.random.Generator(np.random.PCG64([seed, b, 1]))
    k = rng.part_size(n, n2, seed, b, mode)
    if k <= len(resample):
        old = np.delete(resample, gen.choice(len(resample), len(resample) - k, replace=False))
    else:
        old = np.concatenate([resample, sample[gen.integers(0, n, k - len(resample))]])
    fresh = delta[gen.integers(0, len(delta), n2 - k)] if len(delta) else delta[:0]
    return np.concatenate([old, fresh]), abs(k - len(resample)) + n2 - k


def pick_c(probability: float) -> float:
    """Sketch factor c with which sketches of c * sqrt(n) items suffice with this probability: the change's deviation is below sqrt(n)."""
    from statistics import NormalDist

    return NormalDist().inv_cdf(0.5 + probability / 2)


@dataclass
class _Part:
    """One generation of one resample: its items by number, and unused random ones in memory."""

    items: np.ndarray
    pool: np.ndarray
    drop: np.ndarray
    add: np.ndarray
    used_drop: int = 0
    used_add: int = 0
    fresh: int = 0


@dataclass
class SketchStore:
    """A resample in generations with two layers.

    For each generation k, drop holds c * sqrt(n) random places of the resample's part, add as many random
    items of the generation itself; deletions and additions use them in order and mark them used. When one
    runs out, the part's disk layer is read or written and the sketch drawn anew; disk_hits counts that. With
    folder the disk layer is files there, else arrays that stand for them.
    """

    c: float = 3.0
    seed: int = 0
    folder: str | None = None
    parts: list[_Part] = field(default_factory=list)
    disk_hits: int = 0
    sketch_hits: int = 0

    def __post_init__(self):
        self.gen = np.random.Generator(np.random.PCG64([self.seed, 77]))

    def _m(self, n: int) -> int:
        return max(1, math.ceil(self.c * math.sqrt(max(1, n))))

    def _sketch(self, part: _Part, drop: bool = True, add: bool = True) -> None:
        if drop:
            part.drop = self.gen.permutation(len(part.items))[: self._m(len(part.items))]
            part.used_drop = 0
        if add:
            part.add = part.pool[self.gen.integers(0, len(part.pool), self._m(len(part.pool)))] if len(part.pool) else part.pool[:0]
            part.used_add = 0

    def _commit(self, k: int) -> None:
        self.disk_hits += 1
        if self.folder:
            np.save(os.path.join(self.folder, f"gen={k}.npy"), self.parts[k].items)

    @property
    def size(self) -> int:
        return sum(len(p.items) for p in self.parts)

    def values(self) -> np.ndarray:
        return np.concatenate([p.items for p in self.parts]) if self.parts else np.zeros(0)

    def delete(self, k: int, count: int) -> np.ndarray:
        """Take count random items out of generation k and return them."""
        part, gone = self.parts[k], []
        while count:
            room = len(part.drop) - part.used_drop
            if not room:
                self._commit(k)
                self._sketch(part, add=False)
                room = len(part.drop)
            take = min(count, room)
            at = part.drop[part.used_drop : part.used_drop + take]
            gone.append(part.items[at])
            keep = np.ones(len(part.items), bool)
            keep[at] = False
            moved = np.cumsum(keep) - 1
            part.items = part.items[keep]
            part.drop = np.concatenate([part.drop[: part.used_drop], moved[part.drop[part.used_drop + take :]]])
            self.sketch_hits += take
            count -= take
        return np.concatenate(gone) if gone else part.items[:0]

    def add(self, k: int, count: int) -> np.ndarray:
        """Add count random draws of generation k's pool and return them."""
        part, fresh = self.parts[k], []
        while count:
            room = len(part.add) - part.used_add
            if not room:
                self._commit(k)
                self._sketch(part, drop=False)
                room = len(part.add)
            take = min(count, room)
            fresh.append(part.add[part.used_add : part.used_add + take])
            part.used_add += take
            self.sketch_hits += take
            count -= take
        new = np.concatenate(fresh) if fresh else part.items[:0]
        part.items = np.concatenate([part.items, new])
        part.fresh += len(new)
        return new

    def grow(self, delta: np.ndarray, b: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Make this a resample of all generations and delta; returns (items dropped, items added).

        Sizes of all parts are one multinomial draw over the generations' shares.
        """
        pools = [len(p.pool) for p in self.parts] + [len(delta)]
        n2 = sum(pools)
        sizes = rng.split_draws(n2, pools, 1, self.seed * 1_000_003 + 31 * len(pools) + b)[0].tolist()
        dropped, added = [], []
        for k, part in enumerate(self.parts):
            change = sizes[k] - len(part.items)
            if change < 0:
                dropped.append(self.delete(k, -change))
            elif change > 0:
                added.append(self.add(k, change))
        part = _Part(np.zeros(0), delta, np.zeros(0, np.int64), np.zeros(0))
        part.items = delta[self.gen.integers(0, len(delta), sizes[-1])] if len(delta) else delta
        self.parts.append(part)
        self._sketch(part)
        added.append(part.items)
        self.close_iteration()
        return (np.concatenate(dropped) if dropped else np.zeros(0)), np.concatenate(added)

    def close_iteration(self) -> None:
        """Fill sketches up again by substitution: each item that came in this round takes the place of a random sketched one with the chance that a sketch of its size has; the parts are not read.

        A drop sketch that is still short waits: delete reads the part, and counts that, when it runs out.
        """
        for part in self.parts:
            want, left = self._m(len(part.items)), part.drop[part.used_drop :]
            fresh = np.arange(len(part.items) - part.fresh, len(part.items))
            take = fresh[self.gen.random(len(fresh)) < min(1.0, want / max(1, len(part.items)))][:want]
            room = max(0, want - len(left))
            put, over = take[:room], take[room:]
            if len(over) and len(left):
                left = left.copy()
                left[self.gen.choice(len(left), min(len(over), len(left)), replace=False)] = over[: len(left)]
            part.drop, part.used_drop, part.fresh = np.concatenate([left, put]), 0, 0


def maintained_sizes(values: DataFrame, x: str, replicates: int, first: int, seed: int = 0, mode: str = "plain", c: float = 3.0) -> DataFrame:
    """(b, n, n2, touched, disk_hits) of replicates of the first rows of values (pos, x), grown to all rows, each in one group task."""
    cross = values.select("pos", F.col(x).cast("double").alias("x")).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(replicates - 1))))

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values("pos")
        b, v = int(pdf["b"].iloc[0]), pdf["x"].to_numpy()
        s, d = v[:first], v[first:]
        if mode == "plain":
            gen = np.random.Generator(np.random.PCG64([seed, b]))
            out, touched = maintain_plain(s[gen.integers(0, len(s), len(s))], s, d, seed, b)
            return pd.DataFrame({"b": [b], "n": [len(s)], "n2": [len(out)], "touched": [touched], "disk_hits": [0]})
        store = SketchStore(c, seed * 1000 + b)
        store.grow(s, b)
        dropped, added = store.grow(d, b)
        return pd.DataFrame({"b": [b], "n": [len(s)], "n2": [store.size], "touched": [len(dropped) + len(added)], "disk_hits": [store.disk_hits]})

    return cross.groupBy("b").applyInPandas(run, "b long, n long, n2 long, touched long, disk_hits long")


class ResampleTables:
    """Fixed-size resamples of a growing sample, as tables in a shared folder.

    The rows of each generation are dealt into parts of about rows_per_part; a cell is one part of one generation.
    A state has a row for each replicate and cell: the number n of its draws from the cell and their total; layer
    one, drop and add, c * sqrt(size) unused draws to take out and to put in; layer two, all its items. Layers are
    columns of one table, so what does not need the items does not read them. Sizes of all cells in all replicates
    are one multinomial draw each, on the driver: replicates x cells numbers.
    """

    STATE = "b int, gen int, part int, n long, total double, drop array<double>, add array<double>, items array<double>"

    def __init__(self, spark, path: str, replicates: int, c: float = 4.0, rows_per_part: int = 50_000, seed: int = 0):
        self.spark, self.path, self.replicates, self.c, self.rows_per_part, self.seed = spark, path, replicates, c, rows_per_part, seed
        self.cells: dict[tuple[int, int], int] = {}
        self.gen = 0
        self.disk_hits = 0

    def _pool(self, values: DataFrame, gen: int, path: str) -> dict[tuple[int, int], int]:
        """Write the values (x, h) of a generation by part; sizes of its cells. h is a hash of a row's id."""
        parts = max(1, math.ceil(values.count() / self.rows_per_part))
        dealt = values.select("x", F.pmod("h", F.lit(parts)).cast("int").alias("part")).repartition(parts, "part")
        dealt.groupBy("part").agg(F.collect_list("x").alias("xs")).select(F.lit(gen).alias("gen"), "part", "xs").write.parquet(path)
        return {(gen, r["part"]): r["n"] for r in self.spark.read.parquet(path).select("part", F.size("xs").alias("n")).collect()}

    def _wanted(self, cells: dict[tuple[int, int], int]) -> dict[tuple[int, int], np.ndarray]:
        keys = sorted(cells)
        quotas = rng.split_draws(sum(cells.values()), [cells[k] for k in keys], self.replicates, self.seed + 101 * len(keys))
        return {k: quotas[:, i] for i, k in enumerate(keys)}

    def _draw(self, pool: DataFrame, wanted: dict[tuple[int, int], np.ndarray]) -> DataFrame:
        """State rows of all replicates for the cells in pool, drawn from nothing."""
        c, seed = self.c, self.seed

        def run(batches):
            for batch in batches:
                for gen, part, xs in zip(batch.column("gen").to_pylist(), batch.column("part").to_pylist(), batch.column("xs")):
                    v = xs.values.to_numpy(zero_copy_only=False)
                    m, rows = math.ceil(c * math.sqrt(len(v))), []
                    for b, k in enumerate(wanted[gen, part].tolist()):
                        own = np.random.Generator(np.random.PCG64([seed, gen, part, b]))
                        items = v[own.integers(0, len(v), k)]
                        # items are independent draws: those that come first are random ones
                        rows.append((b, gen, part, k, float(items.sum()), items[:m], v[own.integers(0, len(v), m)], items))
                    kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), *[pa.list_(pa.float64())] * 3]
                    yield pa.RecordBatch.from_arrays([pa.array(list(x), k) for x, k in zip(zip(*rows), kinds)], names=["b", "gen", "part", "n", "total", "drop", "add", "items"])

        return pool.mapInArrow(run, self.STATE)

    def grow(self, values: DataFrame) -> None:
        """The first generation: all replicates are drawn and saved."""
        self.cells = self._pool(values, 0, f"{self.path}/pool-0")
        self._draw(self.spark.read.parquet(f"{self.path}/pool-0"), self._wanted(self.cells)).write.parquet(f"{self.path}/state-0")
        self.gen = 1

    def grown(self, delta: DataFrame, how: str = "sketch") -> tuple[DataFrame, int]:
        """(b, gen, part, n, total) of resamples of all rows so far and delta (x, h) together, and the number of items read or drawn for it.

        redraw: all cells are drawn again. items: old cells are cut or drawn to their new size, reading their
        items. sketch: they are changed by unused draws of layer one alone; cells where these run out read their
        items, which disk_hits counts. The state on disk stays as it is, so ways can be compared.
        """
        run = f"{self.path}/{how}-{uuid.uuid4().hex[:8]}"
        fresh = self._pool(delta, self.gen, f"{run}/pool")
        cells = self.cells | fresh
        wanted = self._wanted(cells)
        new_pool, old_pool = self.spark.read.parquet(f"{run}/pool"), self.spark.read.parquet(f"{self.path}/pool-0")
        self._draw(new_pool, wanted).write.parquet(f"{run}/new")
        touched = sum(int(wanted[k].sum()) for k in fresh)
        if how == "redraw":
            self._draw(old_pool, wanted).write.parquet(f"{run}/old")
            touched += sum(int(wanted[k].sum()) for k in self.cells)
        else:
            sizes = [(b, *k, int(w)) for k, ws in wanted.items() if k in self.cells for b, w in enumerate(ws)]
            state = self.spark.read.parquet(f"{self.path}/state-0").join(self.spark.createDataFrame(sizes, "b int, gen int, part int, want long"), ["b", "gen", "part"])
            less, more = F.greatest(F.col("n") - F.col("want"), F.lit(0)).cast("int"), F.greatest(F.col("want") - F.col("n"), F.lit(0)).cast("int")
            total = lambda xs: F.aggregate(xs, F.lit(0.0), lambda a, x: a + x)
            if how == "items":
                # a cell that shrinks is cut; one that grows is drawn on, from its own pool
                cut = state.where("want <= n").withColumn("items", F.slice("items", F.lit(1), F.col("want").cast("int")))
                on = state.where("want > n").join(old_pool, ["gen", "part"])
                on = on.withColumn("items", F.concat("items", F.transform(F.sequence(F.col("n") + 1, F.col("want")), lambda i: F.element_at("xs", (F.pmod(F.xxhash64(F.lit(self.seed), "b", i), F.size("xs")) + 1).cast("int")))))
                kept = cut.unionByName(on.drop("xs")).select("b", "gen", "part", F.col("want").alias("n"), total(F.col("items")).alias("total"), "drop", "add", "items")
                touched += self.replicates * sum(self.cells.values())
            else:
                enough = (F.size("drop") >= less) & (F.size("add") >= more)
                from_sketch = state.where(enough)
                taken, put = F.slice("drop", F.lit(1), less), F.slice("add", F.lit(1), more)
                rest = lambda c, k: F.slice(c, k + 1, F.size(c))
                kept = from_sketch.select("b", "gen", "part", F.col("want").alias("n"), (F.col("total") - total(taken) + total(put)).alias("total"), rest("drop", less).alias("drop"), rest("add", more).alias("add"), taken.alias("gone"), put.alias("come"))
                short = state.where(~enough).select("b", "gen", "part").collect()
                self.disk_hits = len(short)
                if short:
                    redone = self._draw(old_pool, wanted).join(F.broadcast(self.spark.createDataFrame(short, "b int, gen int, part int")), ["b", "gen", "part"])
                    none = F.lit(None).cast("array<double>")
                    kept = kept.unionByName(redone.drop("items").withColumn("gone", none).withColumn("come", none))
                touched += sum(int(abs(wanted[k] - n).sum()) for k, n in self.cells.items())
            kept.write.parquet(f"{run}/old")
        slim = [self.spark.read.parquet(f"{run}/{t}").select("b", "gen", "part", "n", "total") for t in ("old", "new")]
        return slim[0].unionByName(slim[1]), touched


def shared_prefix(n: int, k: int) -> float:
    """Chance that k draws from n items are pairwise distinct: that a resample can share k items as they are."""
    if k > n:
        return 0.0
    return math.exp(math.lgamma(n + 1) - math.lgamma(n - k + 1) - k * math.log(n))


def work_saved(n: int, y: float) -> float:
    """Share of work that a shared fraction y saves on average; y * n is rounded down to items."""
    k = math.floor(y * n)
    return shared_prefix(n, k) * k / n


def optimal_share(n: int) -> tuple[int, float]:
    """Items to share for the largest saving, and that saving: binary search over where it stops growing."""
    lo, hi = 1, n
    while lo < hi:
        k = (lo + hi) // 2
        if k + 1 <= n and work_saved_items(n, k + 1) > work_saved_items(n, k):
            lo = k + 1
        else:
            hi = k
    return lo, work_saved_items(n, lo)


def work_saved_items(n: int, k: int) -> float:
    return shared_prefix(n, k) * k / n


def bootstrap_shared(values: np.ndarray, replicates: int, k: int, seed: int = 0, decorrelate: bool = False) -> tuple[np.ndarray, float, int]:
    """Means of replicates whose first k draws are common: (means, c_v, draws made). A shared prefix correlates replicates by k / n; decorrelate corrects c_v."""
    gen = np.random.Generator(np.random.PCG64(seed))
    n = len(values)
    prefix = values[gen.integers(0, n, k)].sum()
    means = np.array([(prefix + values[gen.integers(0, n, n - k)].sum()) / n for _ in range(replicates)])
    cv = float(means.std() / abs(means.mean()))
    return means, cv / math.sqrt(1 - k / n) if decorrelate else cv, k + replicates * (n - k)
