"""A sample that grows with a stream: micro-batches are increments, states are merged, the stream ends when the error is small."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.functions import accuracy
from approxboot.functions.statistics import Statistic
from approxboot.operators.maintain import merge_states
from approxboot.operators.resample import bootstrap_states


def stream_parquet(spark: SparkSession, path: str, like: DataFrame, name_filter: str | None = None, files_per_trigger: int | None = None) -> DataFrame:
    """Stream of Parquet files with ts as a timestamp, which watermarks need."""
    reader = spark.readStream.schema(like.schema)
    if name_filter:
        reader = reader.option("pathGlobFilter", name_filter)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


@dataclass
class EarlyStream:
    """foreachBatch target: rows it has merged so far, the error after each batch, and whether to stop.

    Weights are functions of row ids, so a batch that is replayed after a failure gives the same states; a
    batch number seen before is not merged again.
    """

    stat: Statistic
    ids: list[str]
    sigma: float
    B: int = 30
    kind: str = "xx"
    states: list = field(default_factory=list)
    errors: list = field(default_factory=list)
    last_batch: int = -1
    done: bool = False

    def __call__(self, batch: DataFrame, number: int) -> None:
        if self.done or number <= self.last_batch:
            return
        spark = batch.sparkSession
        new = bootstrap_states(batch, self.stat, self.ids, self.B, kind=self.kind)
        if self.states:
            new = merge_states(spark.createDataFrame(self.states, new.schema), new, self.stat, ["b"])
        # B rows of sums
        self.states, schema = new.collect(), new.schema
        self.last_batch = number
        if self.states:
            row = accuracy.summarise(self.stat.answer(spark.createDataFrame(self.states, schema), ["b"])).first()
            self.errors.append((number, row["value"], row["cv"]))
            self.done = row["cv"] is not None and row["cv"] <= self.sigma


def run_until(query_of, target: EarlyStream, poll_s: float = 0.2):
    """Start query_of(target) and stop it, from outside its callback, once target is done; returns target."""
    import time

    query = query_of(target)
    while query.isActive:
        if target.done:
            query.stop()
            break
        query.awaitTermination(poll_s)
        time.sleep(0)
    if query.exception():
        raise query.exception()
    return target


def windowed_early(events: DataFrame, stat: Statistic, ids: list[str], width: str, B: int = 30, late: str = "1 hour", kind: str = "xx") -> DataFrame:
    """(start, b, theta) of event-time windows in one streaming aggregation of replicates' states."""
    from approxboot.operators.resample import replicated

    weighted = replicated(events.withWatermark("ts", late), ids, B, kind=kind)
    states = weighted.groupBy(F.window("ts", width).alias("win"), "b").agg(*stat.aggs(F.col("w")))
    return stat.answer(states.withColumn("start", F.col("win.start")), ["start", "b"])
