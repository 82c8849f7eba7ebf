"""What runs cost: wall time, rows and bytes, work saved, jobs, shuffles."""

from __future__ import annotations

import time
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame


@contextmanager
def timed(out: dict, key: str):
    begin = time.perf_counter()
    try:
        yield
    finally:
        out[key] = time.perf_counter() - begin


def speed_up(base: float, ours: float) -> float:
    return base / ours if ours else float("inf")


def processed(B: int, n: int) -> int:
    """Rows that a bootstrap of B resamples of n rows handles."""
    return B * n


def plan_facts(df: DataFrame) -> dict:
    """Exchanges, Python nodes and pushed or partition filters of a physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange hash") + text.count("Exchange Single") + text.count("Exchange range"), "broadcasts": text.count("BroadcastExchange"), "python": sum(text.count(k) for k in ("ArrowEvalPython", "MapInArrow", "MapInPandas", "FlatMapGroupsInPandas", "BatchEvalPython")), "partition_filters": "PartitionFilters: [isnotnull" in text or "bucket#" in text.split("PartitionFilters: [", 1)[-1].split("]", 1)[0], "text": text}


def measured(spark, run) -> dict:
    """result, seconds, jobs, tasks, most (tasks of the widest stage), rows_read, bytes_read and shuffle_bytes of what run() does, by the engine's own counters of its jobs."""
    sc = spark.sparkContext
    group = f"measured-{uuid.uuid4().hex}"
    begin = time.perf_counter()
    sc.setJobGroup(group, group)
    try:
        result = run()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    out = {"result": result, "seconds": time.perf_counter() - begin, "jobs": 0, "tasks": 0, "most": 0, "rows_read": 0, "bytes_read": 0, "shuffle_bytes": 0}
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    store, tracker, seen = sc._jsc.sc().statusStore(), sc.statusTracker(), set()
    for job in tracker.getJobIdsForGroup(group):
        out["jobs"] += 1
        for stage in tracker.getJobInfo(job).stageIds:
            if stage in seen:
                continue
            seen.add(stage)
            facts = store.lastStageAttempt(stage)
            out["tasks"] += facts.numCompleteTasks()
            out["most"] = max(out["most"], facts.numCompleteTasks())
            out["rows_read"] += facts.inputRecords()
            out["bytes_read"] += facts.inputBytes()
            out["shuffle_bytes"] += facts.shuffleWriteBytes()
    return out
