"""Streaming queries over events, replayed with an availableNow trigger into files or, where rows are few, a memory sink."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.catalog.methods import cents, t
from approxboot.functions import rng
from approxboot.functions import statistics as st
from approxboot.sources.shared import fresh_path
from approxboot.streaming.early import EarlyStream, run_until, stream_parquet

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    like = spark.read.parquet(f"{sf_dir}/events.parquet")
    if all(f.endswith("/events.parquet") for f in like.inputFiles()):  # a single file: its folder, by its name
        return stream_parquet(spark, sf_dir, like, "events.parquet")
    return stream_parquet(spark, f"{sf_dir}/events.parquet", like)


#: State on the executors' disks, in memory of a fixed size: a batch's state is as large as the table.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def replayed(df: DataFrame, mode: str = "append") -> DataFrame:
    """All rows that a stream gives for the input there is now. Appended rows, as many as the input may have, go to files; others, a row for each group, into memory."""
    spark = df.sparkSession
    name, path = f"approxboot_{uuid.uuid4().hex}", fresh_path(spark, "replayed")
    before = {k: spark.conf.get(k, None) for k in STATE}
    try:
        for k, v in STATE.items():
            spark.conf.set(k, v)
        w = df.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True)
        q = w.format("parquet").start(path) if mode == "append" else w.format("memory").start()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(path) if mode == "append" else spark.table(name)


def ntz(c: str):
    return F.col(c).cast("timestamp_ntz")


# windows behind the watermark of the last row stay open in append mode
CLOSED = "< (select max(ts) - interval 1 hour from events)"


@query("strm_tumbling", f"select date_trunc('day', ts) as start, event_type, count(*) as n from events group by 1, 2 having date_trunc('day', ts) + interval 1 day {CLOSED}")
def strm_tumbling(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return replayed(e.select(F.col("w.start").alias("start"), "event_type", "n")).select(ntz("start").alias("start"), "event_type", "n")


@query("strm_complete", "select date_trunc('day', ts) as start, count(*) as n, cast(sum(cast(round(value * 100) as bigint)) as bigint) as cents from events group by 1")
def strm_complete(spark, sf_dir):
    e = events(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum(cents("value")).alias("cents"))
    return replayed(e.select(F.col("w.start").alias("start"), "n", "cents"), "complete").select(ntz("start").alias("start"), "n", "cents")


@query("strm_sliding", f"""with h as (select time_bucket(interval 12 hours, ts, timestamp '2000-01-01') as s from events), w as (select s as start from h union all select s - interval 12 hours from h)
select start, count(*) as n from w group by 1 having start + interval 1 day {CLOSED}""")
def strm_sliding(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return replayed(e.select(F.col("w.start").alias("start"), "n")).select(ntz("start").alias("start"), "n")


@query("strm_session", f"""with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as cut from events),
s as (select user_id, ts, sum(cut) over (partition by user_id order by ts rows unbounded preceding) as k from g)
select user_id, min(ts) as start, count(*) as n from s group by user_id, k having max(ts) + interval 30 minutes {CLOSED}""")
def strm_session(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return replayed(e.select("user_id", F.col("w.start").alias("start"), "n")).select("user_id", ntz("start").alias("start"), "n")


@query("strm_dedup", "select count(*) as n from (select distinct user_id, event_type, date_trunc('hour', ts) from events)")
def strm_dedup(spark, sf_dir):
    e = events(spark, sf_dir).withColumn("hour", F.date_trunc("hour", "ts")).withWatermark("hour", "1 hour").dropDuplicates(["user_id", "event_type", "hour"])
    return replayed(e.select("user_id", "event_type", "hour")).agg(F.count(F.lit(1)).alias("n"))


@query("strm_dedup_watermark", "select count(distinct event_id) as n from events")
def strm_dedup_watermark(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return replayed(e.select("event_id")).agg(F.count(F.lit(1)).alias("n"))


@query("strm_static_join", "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
def strm_static_join(spark, sf_dir):
    joined = events(spark, sf_dir).join(t(spark, sf_dir, "customer", "c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    return replayed(joined.select("c_mktsegment")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("strm_stream_join", "select a.event_id as view, b.event_id as purchase from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'view' and b.event_type = 'purchase'")
def strm_stream_join(spark, sf_dir):
    a = events(spark, sf_dir).where("event_type = 'view'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("view")).withWatermark("at", "1 hour")
    b = events(spark, sf_dir).where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("bt"), F.col("event_id").alias("purchase")).withWatermark("bt", "1 hour")
    j = a.join(b, F.expr("user_id = u and bt >= at and bt <= at + interval 1 hour"))
    return replayed(j.select("view", "purchase"))


@query("strm_late_drop", """with e as (select ts, event_id, event_id % 10 = 0 as late, date_trunc('day', ts) + interval 1 day as closes, date_trunc('day', ts) as start from events),
m as (select max(ts) filter (event_id % 10 > 1) - interval 1 hour as first, max(ts) - interval 1 hour as last from e)
select start, count(*) as n from e, m where closes < last and (not late or closes > first) group by 1""")
def strm_late_drop(spark, sf_dir):
    """Counts by day from files whose rows come late: what is behind the watermark is dropped. A batch drops by the watermark that the batch before it began with, so there are three."""
    path = fresh_path(spark, "late")
    e = t(spark, sf_dir, "events")
    late = F.pmod("event_id", F.lit(10))
    for some in (late > 1, late == 1, late == 0):
        e.where(some).coalesce(1).write.mode("append").parquet(path)
    s = stream_parquet(spark, path, e, files_per_trigger=1).withWatermark("ts", "1 hour")
    g = s.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return replayed(g.select(F.col("w.start").alias("start"), "n"))


W = rng.sql_poisson(rng.sql_uniform("boot", "event_id", "b"))


@query("strm_windowed_bootstrap", f"""with w as (select date_trunc('day', ts) as start, b, {W} as w, cast(round(value * 100) as bigint) as c from events, (select unnest(range(10)) as b))
select start, b, round(sum(w * c) / sum(w), 6) as theta from w where w > 0 group by 1, 2""")
def strm_windowed_bootstrap(spark, sf_dir):
    from approxboot.operators.resample import replicated

    e = replicated(events(spark, sf_dir).select("event_id", "ts", cents("value").alias("c")), ["event_id"], 10, kind="md5")
    stat = st.mean("c")
    g = e.groupBy(F.window("ts", "1 day").alias("win"), "b").agg(*stat.aggs(F.col("w")))
    out = replayed(stat.answer(g.withColumn("start", F.col("win.start")), ["start", "b"]), "complete")
    return out.select(ntz("start").alias("start"), F.col("b").cast("long").alias("b"), F.round("theta", 6).alias("theta"))


@query("strm_early_mean", "select cast(count(*) as bigint) as total, round(avg(value), 6) as mean_true, true as met, true as stopped_early, true as near from events")
def strm_early_mean(spark, sf_dir):
    """An early mean from files replayed one at a time, for an error of 0.1: whether the stream ended before its last file once the error was met, and the mean lies within four errors of the truth."""
    path = fresh_path(spark, "replay")
    e = t(spark, sf_dir, "events")
    e.withColumn("f", F.pmod(F.xxhash64("event_id"), F.lit(8))).repartition(8, "f").drop("f").write.parquet(path)
    total, truth = e.agg(F.count(F.lit(1)), F.avg("value")).first()
    target = EarlyStream(st.mean("value"), ["event_id"], 0.1)
    source = stream_parquet(spark, path, e, files_per_trigger=1)
    check = fresh_path(spark, "early")
    start = lambda sink: source.writeStream.foreachBatch(sink).option("checkpointLocation", check).trigger(availableNow=True).start()
    run_until(start, target)
    number, value, cv = target.errors[-1]
    return spark.createDataFrame([(total, round(truth, 6), cv <= 0.1, number < 7, abs(value / truth - 1) <= 4 * max(cv, 0.02))], "total long, mean_true double, met boolean, stopped_early boolean, near boolean")


@query("strm_stateful", "select user_id, count(*) as n, round(sum(cast(round(value * 100) as bigint)) / count(*) / 100.0, 6) as mean from events group by 1")
def strm_stateful(spark, sf_dir):
    """Running mean of each user in custom state: the last row of each user is the mean of all."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        n, s = state.get if state.exists else (0, 0)
        for pdf in frames:
            n, s = n + len(pdf), s + int((pdf["value"] * 100).round().astype("int64").sum())
        state.update((n, s))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "s": [s]})

    e = events(spark, sf_dir).select("user_id", "value").groupBy("user_id")
    out = replayed(e.applyInPandasWithState(step, "user_id long, n long, s long", "n long, s long", "update", GroupStateTimeout.NoTimeout), "update")
    last = out.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("s", "n").alias("s"))
    return last.select("user_id", "n", F.round(F.col("s") / F.col("n") / 100.0, 6).alias("mean"))
