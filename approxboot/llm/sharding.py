"""Exact uniform shuffle into shards of fixed size.

A matrix that says how many rows each source block sends to each shard is drawn from the multivariate
hypergeometric law, which is the law of those counts under a uniform permutation of all rows. Inside a
block rows are permuted and dealt out by the matrix, then exchanged, then permuted again in the shard.
"""

from __future__ import annotations

import random
from math import exp, lgamma

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import ensure_checkpoint, table


def _log_choose(n: int, k: int) -> float:
    return lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1)


def hypergeometric(rng: random.Random, good: int, bad: int, draws: int) -> int:
    """Good items among draws without replacement, by inversion outward from the mode."""
    low, high = max(0, draws - bad), min(good, draws)
    if low == high:
        return low
    mode = min(high, max(low, (draws + 1) * (good + 1) // (good + bad + 2)))
    top = exp(_log_choose(good, mode) + _log_choose(bad, draws - mode) - _log_choose(good + bad, draws))
    u = rng.random() - top
    left = right = mode
    p_left = p_right = top
    while u >= 0 and (left > low or right < high):
        if right < high:
            p_right *= (good - right) * (draws - right) / ((right + 1) * (bad - draws + right + 1))
            right += 1
            u -= p_right
            if u < 0:
                return right
        if left > low:
            p_left *= left * (bad - draws + left) / ((good - left + 1) * (draws - left + 1))
            left -= 1
            u -= p_left
            if u < 0:
                return left
    return mode


def communication_matrix(block_sizes: list[int], shard_sizes: list[int], seed: int) -> list[list[int]]:
    """Rows per block and shard with these margins; blocks and shards are split in halves, so depth is logarithmic."""
    rng = random.Random(seed)
    out = [[0] * len(shard_sizes) for _ in block_sizes]

    def deal(lo: int, hi: int, room: list[int]) -> None:
        if hi - lo == 1:
            out[lo] = room
            return
        mid = (lo + hi) // 2
        need, rest = sum(block_sizes[lo:mid]), sum(room)
        first = []
        for r in room:
            k = hypergeometric(rng, r, rest - r, need)
            first.append(k)
            need, rest = need - k, rest - r
        deal(lo, mid, first)
        deal(mid, hi, [r - k for r, k in zip(room, first)])

    if block_sizes:
        deal(0, len(block_sizes), list(shard_sizes))
    return out


def uniform_shards(df: DataFrame, key_cols: list[str], shards: int, seed: int = 17, rows_per_sort: int = 500_000) -> DataFrame:
    """Add shard and slot to df: every assignment with shard sizes at most one apart is equally likely.

    Shards 0 to (rows mod shards) - 1 hold one row more. Slots run from 0 without a gap. Nulls in any
    column are ordinary values, repeated rows get places of their own, an empty table gives an empty one.
    Columns named shard or slot are replaced, others may have any name. df is checkpointed first, so that counting and dealing see
    the same blocks, whatever is lost meanwhile; give it slim rows and join large columns back by key.
    """
    spark = df.sparkSession
    ensure_checkpoint(spark)
    df = df.drop("shard", "slot")
    # the row travels as one column, so that its names meet none of those below
    fixed = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row")).checkpoint()
    here = F.spark_partition_id()
    sizes = {r["blk"]: r["n"] for r in fixed.groupBy(here.alias("blk")).agg(F.count(F.lit(1)).alias("n")).collect()}
    blocks = sorted(sizes)
    total = sum(sizes.values())
    targets = [total // shards + (s < total % shards) for s in range(shards)]
    matrix = communication_matrix([sizes[b] for b in blocks], targets, seed)
    ends = []
    for b, row in zip(blocks, matrix):
        acc, cum = 0, []
        for k in row:
            acc += k
            cum.append(acc)
        ends.append((b, cum))
    # one row for each block of the input: as long as the list of its partitions, which the driver holds anyway
    plan = spark.createDataFrame(ends or [(0, [0] * shards)], "blk int, ends array<long>")
    mixed = fixed.withColumn("_r", F.xxhash64(F.lit(seed), *[F.col(f"row.`{c}`") for c in key_cols], F.monotonically_increasing_id()))
    mixed = mixed.sortWithinPartitions("_r").withColumn("_m", F.monotonically_increasing_id())
    mixed = mixed.withColumn("blk", F.shiftright("_m", 33).cast("int")).withColumn("_k", F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)))
    dealt = mixed.join(F.broadcast(plan), "blk").withColumn("shard", F.size(F.filter("ends", lambda e: e <= F.col("_k"))))
    # second permutation: buckets of the random order are counted, offset and ranked, so no shard is one task
    pieces = max(1, -(-total // shards // rows_per_sort), 16)
    dealt = dealt.withColumn("_q", F.xxhash64(F.lit(seed + 1), "_r", "_m"))
    dealt = dealt.withColumn("_piece", F.pmod(F.shiftright("_q", 20), F.lit(pieces)).cast("int"))
    counts = dealt.groupBy("shard", "_piece").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy("shard").orderBy("_piece").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("_before", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    rank = F.row_number().over(Window.partitionBy("shard", "_piece").orderBy("_q", "_m"))
    ranked = dealt.select("row", "shard", "_piece", rank.alias("_rank"))
    # shards x pieces rows, each counting about rows_per_sort rows
    placed = ranked.join(F.broadcast(offsets), ["shard", "_piece"])
    return placed.select("row.*", "shard", (F.col("_before") + F.col("_rank") - 1).cast("long").alias("slot"))


def documents_to_shards(docs: DataFrame, shards: int = 8, seed: int = 17) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) of every row of docs under the law of equal row counts."""
    text = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    slim = docs.select("doc_id", (F.octet_length(F.coalesce("text", F.lit(""))) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    out = uniform_shards(slim, ["doc_id", "text_crc32"], shards, seed)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))


def op6_hypergeometric_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in eight shards under the law of equal row counts; null texts are empty, repeated rows get slots of their own."""
    return documents_to_shards(table(spark, sf_dir, "documents"))


QUERIES = {"op6_hypergeometric_shards": op6_hypergeometric_shards}
ORACLES: dict[str, str] = {}
