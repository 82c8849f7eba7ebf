"""Helpers that the text operators share."""

from __future__ import annotations

import os
import tempfile
import uuid

import pyarrow as pa

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot import ship_package


#: Rows of a batch that goes to a Python worker: texts can be long, and two copies of a batch are held.
BATCH_ROWS = 1_000


def prepare(spark: SparkSession) -> None:
    """What the operators' Python tasks need of a session: the package, and batches of bounded size."""
    ship_package(spark)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in local mode one of our own where it is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = os.path.join(tempfile.gettempdir(), "approxboot-checkpoints")
    return root


def ensure_checkpoint(spark: SparkSession) -> None:
    """DataFrame.checkpoint() needs a directory on the context; the session's own setting comes first."""
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(shared_root(spark))


def _written(df: DataFrame, what: str) -> tuple[DataFrame, str]:
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def written(df: DataFrame, what: str) -> DataFrame:
    """Cut the lineage of df by a Parquet table in the shared folder, and read that."""
    return _written(df, what)[0]


def free_names(df: DataFrame, *names: str) -> list[str]:
    """The names, longer by underscores where df has columns called so."""
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n.lower() in taken:
            n += "_"
        out.append(n)
    return out


class Scratch:
    """Tables that a computation writes and needs no longer once its result is written."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def written(self, df: DataFrame, what: str) -> DataFrame:
        out, path = _written(df, what)
        self.paths.append(path)
        return out

    def clear(self) -> None:
        """Delete what was written. Nothing that is still to be computed may read it."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for p in self.paths:
            path = jvm.org.apache.hadoop.fs.Path(p)
            path.getFileSystem(conf).delete(path, True)
        self.paths = []


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


#: Edges that one task joins up at most: 16 bytes each. More go the distributed way.
LOCAL_EDGES = 500_000


def _union_find(batches):
    """(node, root) of all edges (u, v) that the task is given."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent[up] if up in parent else up
        return x

    for batch in batches:
        for u, v in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist()):
            a, b = find(u), find(v)
            if a != b:
                parent[max(a, b)] = min(a, b)
    nodes = list(parent)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([find(x) for x in nodes], pa.int64())], names=["node", "root"])


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Components of an undirected graph, as (node, root): root is the smallest node that can be reached.

    Up to LOCAL_EDGES edges, which are counted, are joined up in one task. More go through alternating
    large-star and small-star passes; each is a grouped minimum and an equi-join, and is written to the
    shared folder, so neither lineage nor any group is held in one task. Nulls and loops in edges are
    ignored. No edges: no rows.
    """
    spark = edges.sparkSession
    e = edges.select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("v"))
    e = written(e.where("u is not null and v is not null and u <> v").distinct(), "cc")
    if e.count() <= LOCAL_EDGES:
        return e.repartition(1).mapInArrow(_union_find, "node long, root long")
    before = None
    while True:
        # large star: every node tells its larger neighbours about its smallest one
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        big = e.select(F.col("v").alias("u"), F.col("u").alias("w")).join(least, "u").select(F.col("w").alias("u"), F.col("m").alias("v"))
        big = big.where("u <> v").distinct()
        # small star: smaller neighbours and the node itself point at the smallest
        low = big.groupBy("u").agg(F.min("v").alias("m"))
        small = big.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        e = written(small, "cc")
        state = tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())
        if state == before:
            break
        before = state
    roots = e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
