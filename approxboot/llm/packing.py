"""Best-fit packing of token sequences with certified bin counts.

Pieces are packed by best-fit decreasing inside partitions. Dual-feasible functions give each partition a
lower bound on its bins. A partition that meets its bound is certified and keeps its bins, all but the emptiest,
which only its rounding left; a partition above its bound gives up all bins with room. What was given up is
dealt into fewer, larger partitions and packed again, until all are certified or one partition is left.
"""

from __future__ import annotations

import math
import zlib
from typing import Any

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.llm.common import table, written
from approxboot.llm.encoding import encoder, slices

CAPACITY = 4096


def lower_bound(lengths: np.ndarray, counts: np.ndarray, capacity: int = CAPACITY) -> int:
    """Bins that any packing of these lengths (each counts times) needs, by dual-feasible functions.

    A dual-feasible function maps sizes in [0, 1] so that whatever fits a bin sums to 1 at most; the sum
    over all items is then a bound. Used: the identity, thresholds that round large items up to 1 and drop
    small ones, and rounding down to multiples of 1/k.
    """
    if not len(lengths):
        return 0
    x = np.asarray(lengths, np.int64)
    n = np.asarray(counts, np.int64)
    best = -(-int((x * n).sum()) // capacity)
    for cut in np.unique(np.concatenate([x[2 * x <= capacity], capacity - x[2 * x > capacity]])):
        value = np.where(x > capacity - cut, capacity, np.where(x >= cut, x, 0))
        best = max(best, -(-int((value * n).sum()) // capacity))
    for k in range(1, 21):
        whole = (k + 1) * x % capacity == 0
        value = np.where(whole, x * k, (k + 1) * x // capacity * capacity)  # in units of 1 / (k * capacity)
        best = max(best, -(-int((value * n).sum()) // (k * capacity)))
    return int(best)


def best_fit_decreasing(lengths: np.ndarray, capacity: int = CAPACITY) -> np.ndarray:
    """Bin of each item: largest first, into the fullest bin with room. Open rooms are bits of one integer."""
    bins = np.zeros(len(lengths), np.int64)
    open_bins: dict[int, list[int]] = {}
    rooms, opened = 0, 0
    order = np.argsort(-lengths, kind="stable")
    for i, size in zip(order.tolist(), lengths[order].tolist()):
        fit = rooms >> size
        if fit:
            room = size + ((fit & -fit).bit_length() - 1)
            stack = open_bins[room]
            b = stack.pop()
            if not stack:
                rooms &= ~(1 << room)
        else:
            room, b = capacity, opened
            opened += 1
        bins[i] = b
        room -= size
        if room:
            open_bins.setdefault(room, []).append(b)
            rooms |= 1 << room
    return bins


def _pack_group(keys: list[str], capacity: int):
    def run(key: tuple[Any, ...], pdf: pd.DataFrame) -> pd.DataFrame:
        lengths = pdf["length"].to_numpy(np.int64)
        bins = best_fit_decreasing(lengths, capacity)
        order = np.argsort(bins, kind="stable")
        sizes = lengths[order]
        total = np.cumsum(sizes) - sizes
        first = np.concatenate([[True], bins[order][1:] != bins[order][:-1]])
        offset = np.empty(len(bins), np.int64)
        offset[order] = total - np.maximum.accumulate(np.where(first, total, 0))
        used = np.bincount(bins, weights=lengths).astype(np.int64)
        values, counts = np.unique(lengths, return_counts=True)
        gap = len(used) - lower_bound(values, counts, capacity)
        facts = {"length": lengths.astype(np.int32), "grp": key[0], "bin": bins.astype(np.int32), "offset": offset.astype(np.int32), "gap": np.int32(gap), "room": (capacity - used[bins]).astype(np.int32), "emptiest": bins == used.argmin()}
        return pd.DataFrame({k: pdf[k] for k in keys} | facts)

    return run


def pack(pieces: DataFrame, capacity: int = CAPACITY, keys: list[str] | None = None, per_group: int = 100_000, rounds: int = 3, seed: int = 5) -> DataFrame:
    """(keys, sequence_id, offset, round, gap) for pieces (keys, length 1 to capacity); keys, piece_key by default, name a piece uniquely and are not null.

    Pieces are dealt at random into groups of about per_group, four times as many in each further round, and
    each group is packed in one task. round and gap say when a piece's place was settled, and how many bins its
    group then had above its bound: 0 is a certificate. The last round's packing stands. A sequence_id holds
    round, group and bin, so no two bins share one. An empty table gives an empty one; equal lengths are
    interchangeable and keep the order they come in.
    """
    keys = keys or ["piece_key"]
    kinds = ", ".join(f"`{k}` {pieces.schema[k].dataType.simpleString()}" for k in keys)
    packed_schema = f"{kinds}, length int, grp long, bin int, offset int, gap int, room int, emptiest boolean"
    pool, done = pieces.select(*keys, F.col("length").cast("int").alias("length")), None
    for r in range(rounds):
        groups = max(1, math.ceil(pool.count() / (per_group << 2 * r)))
        grouped = pool.withColumn("grp", F.pmod(F.xxhash64(F.lit(seed + r), *keys), F.lit(groups)))
        packed = written(grouped.groupBy("grp").applyInPandas(_pack_group(keys, capacity), packed_schema), "packing")
        last = r == rounds - 1 or groups == 1
        again = F.lit(False) if last else (F.col("room") > 0) & ((F.col("gap") > 0) | F.col("emptiest"))
        number = F.lit(r << 60) + F.shiftleft("grp", 24) + F.col("bin")
        settled = packed.where(~again).select(*keys, number.cast("long").alias("sequence_id"), F.col("offset").cast("long").alias("offset"), F.lit(r).alias("round"), "gap")
        done = settled if done is None else done.unionByName(settled)
        if last:
            break
        pool = packed.where(again).select(*keys, "length")
    return done


def certificate(packed: DataFrame, pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row (sequences, bound, gap): sequences used against the bound of all pieces together. A histogram has capacity rows at most."""
    hist = pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()
    bound = lower_bound(np.array([r["length"] for r in hist], np.int64), np.array([r["n"] for r in hist], np.int64), capacity)
    used = packed.agg(F.countDistinct("sequence_id").alias("sequences"))
    return used.select("sequences", F.lit(bound).cast("long").alias("bound"), (F.col("sequences") - bound).alias("gap"))


PIECES = "doc_id long, row_key long, piece int, start long, length int, ids_crc32 long"


def _cut(path: str, end_id: int, capacity: int, max_words: int):
    def run(batches):
        enc = encoder(path, "", max_words=max_words)
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            docs, keys = batch.column("doc_id").to_pylist(), batch.column("row_key").to_pylist()
            for lo, hi in slices(texts):
                ids, lengths = enc.encode(texts[lo:hi])
                out = np.full(len(ids) + len(lengths), end_id, "<u4")
                ends = np.cumsum(lengths + 1)
                keep = np.ones(len(out), bool)
                keep[ends - 1] = False
                out[keep] = ids
                view, rows, begin = memoryview(out).cast("B"), [], 0
                for i, end in enumerate(ends.tolist()):
                    for p, a in enumerate(range(begin, end, capacity)):
                        b = min(a + capacity, end)
                        rows.append((docs[lo + i], keys[lo + i], p, a - begin, b - a, zlib.crc32(view[4 * a : 4 * b])))
                    begin = end
                doc, key, piece, start, length, crc = zip(*rows)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(doc, pa.int64()), pa.array(key, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int32()), pa.array(crc, pa.int64())],
                    names=["doc_id", "row_key", "piece", "start", "length", "ids_crc32"],
                )

    return run


def cut_pieces(docs: DataFrame, tokenizer_path: str, end_id: int, capacity: int = CAPACITY, max_words: int = 2_000_000) -> DataFrame:
    """Pieces of all docs (doc_id, text): each document's ids and end_id, cut only where they exceed capacity.

    Written once to the shared folder, so that keys given to rows by position stay the same.
    """
    keyed = docs.select("doc_id", "text", F.monotonically_increasing_id().alias("row_key"))
    return written(keyed.mapInArrow(_cut(tokenizer_path, end_id, capacity, max_words), PIECES), "pieces")


def pack_documents(docs: DataFrame, tokenizer_path: str, end_id: int, capacity: int = CAPACITY, max_words: int = 2_000_000) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset, round, gap) for every piece of docs (doc_id, text).

    A null or empty text is one piece of the end id alone. Rows with one doc_id, or a null one, are documents of
    their own. Texts of any length are cut into as many pieces as they need. Other columns are not looked at; an
    empty table gives an empty one. max_words bounds each worker's cache of words.
    """
    pieces = cut_pieces(docs, tokenizer_path, end_id, capacity, max_words)
    out = pieces.join(pack(pieces, capacity, ["row_key", "piece"]), ["row_key", "piece"])
    return out.select("doc_id", "piece", "start", F.col("length").cast("long").alias("length"), "ids_crc32", "sequence_id", "offset", "round", "gap")


def op4_certified_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of 4096 tokens; beside the contract's columns, round and gap are the certificate of a piece's group."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), 1)


QUERIES = {"op4_certified_packing": op4_certified_packing}
ORACLES: dict[str, str] = {}
