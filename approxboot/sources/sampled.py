"""Where an early answer's rows come from: pre-hashed buckets, lines of text files, or a filter over a whole table.

A source knows the table's number of rows, gives a pilot, and grows its sample by rows not given before. read
counts the rows and bytes that it has touched so far.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.operators.sampling import SampleCursor, choose_sampler
from approxboot.sources import layout, lines

#: Rows that a pilot brings to the driver at most.
PILOT_ROWS = 100_000


class ScanSource:
    """Pairs after parsing: every step is a filter over the whole table."""

    weight = None

    def __init__(self, df: DataFrame, ids: list[str], seed: int = 0, kind: str = "xx", N: int | None = None):
        self.df, self.ids, self.cursor, self.N, self.read = df, ids, SampleCursor(df, ids, seed, kind), N, {"rows": 0, "bytes": None}

    def count(self) -> int:
        self.N = self.N if self.N is not None else self.df.count()
        return self.N

    def pilot(self, share: float) -> DataFrame:
        """Rows of a sample in the order of their uniforms, so that prefixes are samples too."""
        self.read["rows"] += self.count()
        return self.df.withColumn("_u", self.cursor.u()).where(F.col("_u") < share).orderBy("_u").limit(PILOT_ROWS).drop("_u")

    def grow(self, p: float) -> DataFrame:
        self.read["rows"] += self.count()
        return self.cursor.grow(p)


class LayoutSource:
    """Buckets of the pre-hashed layout: a sample reads its own share of the files, growth the next buckets."""

    weight = None

    def __init__(self, spark: SparkSession, path: str, ids: list[str], buckets: int = 100):
        self.spark, self.path, self.ids, self.buckets, self.p = spark, path, ids, buckets, 0.0
        self.sizes = layout.sizes(spark, path)
        self.read = {"rows": 0, "bytes": 0}

    def count(self) -> int:
        return sum(n for n, _ in self.sizes.values())

    def _read(self, low: float, p: float) -> DataFrame:
        for b in range(math.floor(low * self.buckets), math.ceil(p * self.buckets)):
            n, size = self.sizes.get(b, (0, 0))
            self.read["rows"] += n
            self.read["bytes"] += size
        return layout.read_fraction(self.spark, self.path, p, self.buckets, low)

    def pilot(self, share: float) -> DataFrame:
        return self._read(0.0, share).orderBy("u").limit(PILOT_ROWS)

    def grow(self, p: float) -> DataFrame:
        low, self.p = self.p, p
        return self._read(low, p)


class LineSource:
    """Random lines of text files, parsed after they are drawn; their weights even out lengths, for statistics in ratio form.

    Draws of different steps are independent, so a line can be in two of them, as in sampling with replacement.
    The pilot is the first step's beginning: where it is enough, nothing more is read.
    """

    weight = "ht_weight"

    def __init__(self, spark: SparkSession, path: str, parse: Callable[[DataFrame], DataFrame], seed: int = 0, split_bytes: int = 64 << 20, pilot_rows: int = 1_000, copies: int = 1):
        self.copies = copies
        self.spark, self.path, self.parse, self.seed, self.split_bytes, self.pilot_rows = spark, path, parse, seed, split_bytes, pilot_rows
        self.bytes = copies * sum(size for _, size in lines.list_files(path))
        self.ids, self.steps, self.n, self.N, self.held = ["_step", "split", "offset"], 0, 0, None, None
        self.read = {"rows": 0, "bytes": 0}

    def _draw(self, n: int) -> DataFrame:
        got = lines.sample_lines(self.spark, self.path, n, self.seed * 1_000 + self.steps, "back", "weight", self.split_bytes, "allow", self.copies)
        got = self.parse(got).withColumn("_step", F.lit(self.steps))
        self.steps += 1
        self.read["rows"] += n
        self.read["bytes"] += n * 4096  # a line costs a block of the reader
        return got

    def _pilot(self) -> DataFrame:
        if self.held is None:
            drawn = self._draw(self.pilot_rows)
            rows = drawn.collect()
            # bytes over the mean length, which weights give: the mean of 1 / length is that of lengths as drawn
            self.N = max(len(rows), round(self.bytes * sum(r["ht_weight"] for r in rows) / len(rows))) if rows else 0
            self.held = self.spark.createDataFrame(rows, drawn.schema)
        return self.held

    def count(self) -> int:
        self._pilot()
        return self.N

    def pilot(self, share: float) -> DataFrame:
        return self._pilot()

    def grow(self, p: float) -> DataFrame:
        wanted, before = math.ceil(p * self.count()), self.n
        self.n = max(wanted, min(self.pilot_rows, self.N))
        if not before:
            more = self.n - min(self.pilot_rows, self.N)
            return self._pilot().unionByName(self._draw(more)) if more > 0 else self._pilot()
        return self._draw(max(1, self.n - before))


def choose_source(spark: SparkSession, ids: list[str], n: int, df: DataFrame | None = None, layout_path: str | None = None, line_path: str | None = None, parse=None, needs_exact_count: bool = False, load_critical: bool = True, buckets: int = 100, seed: int = 0):
    """The pre-hashed layout where there is one; else lines or pairs by the sampler rule; a filter over the table where nothing else is there."""
    if layout_path:
        return LayoutSource(spark, layout_path, ids, buckets)
    if line_path and (df is None or choose_sampler(needs_exact_count, n, load_critical) == "lines"):
        return LineSource(spark, line_path, parse, seed)
    if df is None:
        raise ValueError("there is neither a layout, nor lines, nor a table")
    return ScanSource(df, ids, seed)
