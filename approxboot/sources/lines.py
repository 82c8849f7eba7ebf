"""Sampling before loading: random lines of text files by seeking, and random rows of Parquet row groups.

Both are Python data sources: a partition for each logical split, which reads only what it samples. Paths are
local ones or URIs of any file system that pyarrow.fs opens (file, s3, gs, hdfs).
"""

from __future__ import annotations

import io

import numpy as np
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def store_of(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path or URI, and the path there."""
    if "://" in path or path.startswith("file:"):
        return fs.FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))
    return fs.LocalFileSystem(), path


def list_files(path: str) -> list[tuple[str, int]]:
    """(file, bytes) of the data files in a folder, or of one file; a last part with * matches names."""
    store, inner = store_of(path)
    folder, _, name = inner.rpartition("/")
    if "*" in name:
        from fnmatch import fnmatch

        found = [f for f in store.get_file_info(fs.FileSelector(folder)) if fnmatch(f.base_name, name)]
    else:
        one = store.get_file_info(inner)
        if one.type == fs.FileType.File:
            return [(one.path, one.size)]
        found = store.get_file_info(fs.FileSelector(inner, recursive=True))
    return sorted((f.path, f.size) for f in found if f.type == fs.FileType.File and not any(p.startswith(("_", ".")) for p in f.path[len(folder) :].split("/")))


def list_splits(path: str, split_bytes: int, copies: int = 1) -> list[tuple[str, int, int, int]]:
    """(file, start, end, file's size) of logical splits; with copies, of files that count as so many files of the same lines."""
    return [(f, a, min(a + split_bytes, size), size) for f, size in list_files(path) * copies for a in range(0, size, split_bytes)]


def quota(weights: list[int], n: int, seed: int) -> list[int]:
    """Sample sizes of splits: one multinomial over their weights."""
    w = np.asarray(weights, float)
    if not len(w) or not w.sum():
        return [0] * len(w)
    return np.random.Generator(np.random.PCG64(seed)).multinomial(n, w / w.sum()).tolist()


class _Split(InputPartition):
    def __init__(self, index: int, path: str, start: int, end: int, size: int, n: int):
        self.index, self.path, self.start, self.end, self.size, self.n = index, path, start, end, size, n


def _line_at(f, at: int, size: int, align: str) -> tuple[int, int] | None:
    """(start, end) of a line for a byte position: the line it lies in (back), or the one after (next)."""
    if align == "back":
        lo = at
        while lo > 0:
            step = max(0, lo - 4096)
            f.seek(step)
            chunk = f.read(lo - step)
            cut = chunk.rfind(b"\n")
            if cut >= 0:
                lo = step + cut + 1
                break
            lo = step
        start = lo
    else:
        if at == 0:
            start = 0
        else:
            f.seek(at - 1)
            f.readline()
            start = f.tell()
    if start >= size:
        return None
    f.seek(start)
    line = f.readline()
    return start, start + len(line)


class LineSampleReader(DataSourceReader):
    """Reads options: path, n, seed, align (next, back), debias (none, reject, weight), split_bytes, max_tries, copies."""

    def __init__(self, options: dict):
        self.o = options
        self.align = options.get("align", "back")
        self.debias = options.get("debias", "none")
        if self.align not in ("next", "back") or self.debias not in ("none", "reject", "weight"):
            raise ValueError("align is next or back; debias is none, reject or weight")

    def partitions(self):
        splits = list_splits(self.o["path"], int(self.o.get("split_bytes", 64 << 20)), int(self.o.get("copies", 1)))
        sizes = quota([e - s for _, s, e, _ in splits], int(self.o["n"]), int(self.o.get("seed", 0)))
        return [_Split(i, *split, k) for i, (split, k) in enumerate(zip(splits, sizes)) if k]

    def read(self, part):
        if not isinstance(part, _Split):  # nothing to read
            return
        gen = np.random.Generator(np.random.PCG64([int(self.o.get("seed", 0)), part.index]))
        tries = int(self.o.get("max_tries", 200)) * part.n
        used: set[int] = set()
        got, shortest = 0, None
        size = part.size
        # small reads: what is sampled is a few hundred bytes in each place
        with io.BufferedReader(store_of(self.o["path"])[0].open_input_file(part.path), 4096) as f:
            if self.debias == "reject":
                shortest = _shortest(f, part.start, part.end, size)
            while got < part.n and tries:
                tries -= 1
                found = _line_at(f, int(gen.integers(part.start, part.end)), size, self.align)
                # a line belongs to the split that holds its first byte
                if not found or found[0] in used or not part.start <= found[0] < part.end:
                    continue
                start, end = found
                if shortest and gen.random() * (end - start) > shortest:
                    continue
                used.add(start)
                got += 1
                f.seek(start)
                text = f.read(end - start).rstrip(b"\r\n").decode("utf-8", "replace")
                yield text, part.index, start, 1.0 / (end - start) if self.debias == "weight" else 1.0
        if got < part.n and self.o.get("short", "error") == "error":
            raise ValueError(f"{part.path} from {part.start} to {part.end}: {got} of {part.n} distinct lines were found in {int(self.o.get('max_tries', 200))} tries for each; ask for fewer lines, or for short=allow")


def _shortest(f, lo: int, hi: int, size: int, looks: int = 64) -> int:
    """Shortest of a few lines spread over a split: the length that rejection accepts for sure."""
    found = [_line_at(f, int(a), size, "back") for a in np.linspace(lo, max(lo, hi - 1), looks)]
    return max(1, min((e - s for s, e in filter(None, found)), default=1))


class LineSampleSource(DataSource):
    """Distinct random lines of text files as (value, split, offset, ht_weight), without reading the files through.

    A line is drawn with a chance that grows with its length (its own for align=back, the line before it for
    align=next): debias=reject evens that out where lengths are near each other, debias=weight gives each
    line the weight 1 / length, for statistics in ratio form. Empty lines, CRLF, a missing last newline and
    lines longer than a split are read as they are. Splits that do not hold as many distinct lines as they are
    asked for raise an error, or give fewer with short=allow. copies reads each file as so many files that hold
    the same lines, without their bytes on disk; each copy has splits of its own.
    """

    @classmethod
    def name(cls):
        return "line_sample"

    def schema(self):
        return "value string, split int, offset bigint, ht_weight double"

    def reader(self, schema):
        return LineSampleReader(self.options)


def sample_lines(spark: SparkSession, path: str, n: int, seed: int = 0, align: str = "back", debias: str = "none", split_bytes: int = 64 << 20, short: str = "error", copies: int = 1) -> DataFrame:
    spark.dataSource.register(LineSampleSource)
    return spark.read.format("line_sample").options(path=path, n=str(n), seed=str(seed), align=align, debias=debias, split_bytes=str(split_bytes), short=short, copies=str(copies)).load()


class _Group(InputPartition):
    def __init__(self, path: str, group: int, n: int, seed: int):
        self.path, self.group, self.n, self.seed = path, group, n, seed


class RowGroupReader(DataSourceReader):
    def __init__(self, options: dict, schema):
        self.o, self.names = options, [f.name for f in schema.fields]

    def partitions(self):
        store, _ = store_of(self.o["path"])
        files = [f for f, _ in list_files(self.o["path"])]
        groups = [(f, g, meta.row_group(g).num_rows) for f in files for meta in [pq.read_metadata(f, filesystem=store)] for g in range(meta.num_row_groups)]
        seed, sizes = int(self.o.get("seed", 0)), [n for _, _, n in groups]
        # rows of a uniform sample without replacement in each group
        n = min(int(self.o["n"]), sum(sizes))
        picked = np.random.Generator(np.random.PCG64(seed)).multivariate_hypergeometric(sizes, n, method="marginals").tolist() if sizes else []
        return [_Group(f, g, k, seed * 1_000_003 + i) for i, ((f, g, _), k) in enumerate(zip(groups, picked)) if k]

    def read(self, part):
        if not isinstance(part, _Group):
            return
        data = pq.ParquetFile(part.path, filesystem=store_of(self.o["path"])[0]).read_row_group(part.group, columns=self.names)
        at = np.sort(np.random.Generator(np.random.PCG64(part.seed)).choice(data.num_rows, part.n, replace=False))
        yield from data.take(at).select(self.names).to_batches()


class RowGroupSource(DataSource):
    """Exactly n rows (all, if there are fewer) without replacement, each set of n equally likely; row groups that get none are not read."""

    @classmethod
    def name(cls):
        return "row_group_sample"

    def reader(self, schema):
        return RowGroupReader(self.options, schema)


def sample_row_groups(spark: SparkSession, path: str, n: int, seed: int = 0, columns: list[str] | None = None) -> DataFrame:
    spark.dataSource.register(RowGroupSource)
    like = spark.read.parquet(path)
    like = like.select(columns) if columns else like
    return spark.read.format("row_group_sample").schema(like.schema).options(path=path, n=str(n), seed=str(seed)).load()


def row_count(path: str) -> int:
    """Rows of Parquet files by their footers."""
    store, _ = store_of(path)
    return sum(pq.read_metadata(f, filesystem=store).num_rows for f, _ in list_files(path) if f.endswith(".parquet"))


def logical_splits(df: DataFrame, rows_per_split: int):
    """Column of a Parquet scan's logical split: file and range of row positions."""
    meta = df.select("*", "_metadata.file_path", "_metadata.row_index")
    return meta.withColumn("split", F.xxhash64("file_path", F.floor(F.col("row_index") / rows_per_split)))
