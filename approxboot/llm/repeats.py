"""Removal of repeated windows by a depth-limited radix order of suffixes.

Only whether two suffixes agree on their first units (bytes, or words) up to the window's length matters, so
suffixes are ordered by most-significant-digit passes no deeper than that, and groups of one drop out after each
pass; groups that are left after the last digit are exactly the repeated windows. Digits are taken where the
content says: the first is the gram at the window's minimizer, so that a run of neighbouring suffixes that share
it is one row; the second is the whole run, which settles runs that repeat as they are; the last is the window
itself, for the suffixes of runs that are still open. Digits are compared by 64-bit hashes, each only within a
group of the digit before it (the last one within a task that holds whole groups).
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.llm.common import Scratch, shuffle_width, table, written
from approxboot.llm.kernels import byte_slices, mix, powers, prefix_of, sliding_min, span_hash, units, INVERSE


@dataclass(frozen=True)
class Depth:
    """Length of the windows that are compared, in units, and of the gram that a window's first digit is."""

    unit: str
    window: int
    gram: int


BYTES, WORDS = Depth("bytes", 400, 32), Depth("words", 50, 8)
#: Bytes of open suffixes that one task groups.
GROUP_BYTES = 32 << 20
#: Texts that are named in a broadcast at most: 16 bytes each.
BROADCAST_IDS = 250_000
#: Different runs of one gram from which its windows are dealt one by one; below that in pieces of CHUNK neighbours.
HOT_KINDS = 20_000
CHUNK = 64
#: What names a text: its doc_id and a hash of its bytes.
KEY = ["doc", "uid"]


def window_runs(values: np.ndarray, at: np.ndarray, window: int, gram: int):
    """Runs of window starts with the same minimizer: (row, first start, number, minimizer's place, gram's hash, prefix hash).

    Every window that lies inside one row belongs to one run; starts are positions in values. The minimizer is
    the leftmost gram of least hash, which the window's units alone decide.
    """
    prefix = prefix_of(values)
    none = np.zeros(0, np.int64)
    if len(values) < window:
        return none, none, none, none, np.zeros(0, np.uint64), prefix
    n = len(values) - gram + 1
    grams = mix((prefix[gram:] - prefix[:-gram]) * powers(len(prefix), INVERSE)[:n])
    bits = max(1, int(n).bit_length())
    ranked = (grams & ~np.uint64((1 << bits) - 1)) | np.arange(n, dtype=np.uint64)
    place = (sliding_min(ranked, window - gram + 1) & np.uint64((1 << bits) - 1)).astype(np.int64)
    row = np.repeat(np.arange(len(at) - 1), np.diff(at))[: len(place)]
    inside = np.arange(len(place)) + window <= at[1:][row]
    new = np.ones(len(place), bool)
    new[1:] = (place[1:] != place[:-1]) | (row[1:] != row[:-1])
    starts = np.flatnonzero(new & inside)
    counted = np.concatenate([[0], np.cumsum(inside)])
    stops = np.concatenate([np.flatnonzero(new), [len(place)]])
    following = stops[np.searchsorted(stops, starts, "right")]
    size = counted[following] - counted[starts]
    return row[starts], starts, size, place[starts], grams[place[starts]], prefix


def run_digests(starts, size, place, grams, prefix, window: int) -> np.ndarray:
    """Hash of all units that a run's windows cover, with where the minimizer lies in them."""
    span = span_hash(prefix, starts, starts + size + window - 1)
    return mix(span + mix(grams + (place - starts).astype(np.uint64)))


RUNS = "doc long, uid long, digit long, run long, start int, size int, rel int"


def _runs(depth: Depth):
    def run(batches):
        for batch in batches:
            column, keys = batch.column("text"), [batch.column(k).to_numpy() for k in KEY]
            for lo, hi in byte_slices(column):
                values, at = units(column, lo, hi, depth.unit)
                row, starts, size, place, grams, prefix = window_runs(values, at, depth.window, depth.gram)
                digest = run_digests(starts, size, place, grams, prefix, depth.window)
                numbers = [starts - at[row], size, place - starts]
                yield pa.RecordBatch.from_arrays(
                    [*[pa.array(k[lo:hi][row]) for k in keys], pa.array(grams.view(np.int64)), pa.array(digest.view(np.int64)), *[pa.array(x.astype(np.int32)) for x in numbers]],
                    names=[*KEY, "digit", "run", "start", "size", "rel"],
                )

    return run


#: A piece of neighbouring windows as bytes: its text's key, its first start and its number of windows.
PIECE = np.dtype([("doc", "<i8"), ("uid", "<i8"), ("start", "<i4"), ("count", "<i4")])


def _pieces(h, start, deal, run, doc, uid):
    """Neighbouring windows of one run that are dealt to one place, as PIECE rows, with that place."""
    cut = np.concatenate([[True], (deal[1:] != deal[:-1]) | (run[1:] != run[:-1])]) if len(h) else np.zeros(0, bool)
    first = np.flatnonzero(cut)
    out = np.zeros(len(first), PIECE)
    out["doc"], out["uid"], out["start"] = doc, uid, start[first]
    out["count"] = np.diff(np.concatenate([first, [len(h)]]))
    return out, deal[first]


def _open_windows(depth: Depth, parts: int):
    """Window hashes of the open runs of each row: (part, pieces, hashes), the latter two as arrays of bytes."""

    def flush(held):
        h, pieces, place = (np.concatenate([x[i] for x in held]) for i in range(3))
        part = (place % np.uint64(parts)).astype(np.int64)
        begin = np.cumsum(pieces["count"]) - pieces["count"]
        order = np.argsort(part, kind="stable")
        count = pieces["count"][order].astype(np.int64)
        ends = np.cumsum(count)
        h = h[np.repeat(begin[order] - (ends - count), count) + np.arange(len(h))]
        ends = np.concatenate([[0], ends])
        cuts = np.searchsorted(part[order], np.arange(parts + 1))
        rows = [(p, pieces[order[a:b]].tobytes(), h[ends[a] : ends[b]].tobytes()) for p, (a, b) in enumerate(zip(cuts, cuts[1:])) if b > a]
        return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], names=["part", "pieces", "hashes"])

    def run(batches):
        held, count = [], 0
        for batch in batches:
            column, opened = batch.column("text"), batch.column("runs")
            docs, uids = (batch.column(k).to_numpy() for k in KEY)
            for lo, hi in byte_slices(column):
                values, at = units(column, lo, hi, depth.unit)
                prefix = prefix_of(values)
                for i in range(lo, hi):
                    items = np.array([(r["start"], r["size"], r["rel"], r["digit"], r["hot"]) for r in opened[i].as_py()], np.int64).reshape(-1, 5)
                    size = items[:, 1]
                    offset = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
                    start = np.repeat(items[:, 0], size) + offset
                    rel = np.repeat(items[:, 2], size) - offset
                    absolute = start + at[i - lo]
                    # windows that agree have their minimizer in the same place
                    h = mix(span_hash(prefix, absolute, absolute + depth.window) + rel.astype(np.uint64))
                    # only windows of one gram and one place of it can agree: they share a part
                    digit, hot = np.repeat(items[:, 3].view(np.uint64), size), np.repeat(items[:, 4] > 0, size)
                    deal = np.where(hot, h, mix(digit + (rel // CHUNK).astype(np.uint64)))
                    held.append((h, *_pieces(h, start, deal, np.repeat(np.arange(len(size)), size), docs[i], uids[i])))
                    count += len(h)
                    if count > 400_000:
                        yield flush(held)
                        held, count = [], 0
        if count:
            yield flush(held)

    return run


SPANS = "doc long, uid long, start int, stop int"


def _repeated_windows(window: int):
    """Windows of a task that occur twice, as spans, neighbours merged."""

    def run(batches):
        pieces, h = [], []
        for batch in batches:
            for p, x in zip(batch.column("pieces"), batch.column("hashes")):
                pieces.append(np.frombuffer(p.as_buffer(), PIECE))
                h.append(np.frombuffer(x.as_buffer(), "<u8"))
        if not h:
            return
        h, pieces = np.concatenate(h), np.concatenate(pieces)
        order = np.argsort(h, kind="stable")
        s = h[order]
        same = s[1:] == s[:-1]
        twice = np.zeros(len(s), bool)
        twice[1:] |= same
        twice[:-1] |= same
        at = np.sort(order[twice])
        if not len(at):
            return
        ends = np.cumsum(pieces["count"])
        which = np.searchsorted(ends, at, "right")
        start = pieces["start"][which] + (at - (ends - pieces["count"])[which])
        doc, uid = pieces["doc"][which], pieces["uid"][which]
        order = np.lexsort((start, uid, doc))
        doc, uid, start = doc[order], uid[order], start[order]
        new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (uid[1:] != uid[:-1]) | (start[1:] > start[:-1] + window)])
        first = np.flatnonzero(new)
        last = np.concatenate([first[1:], [len(uid)]]) - 1
        for lo in range(0, len(first), 50_000):
            f, t = first[lo : lo + 50_000], last[lo : lo + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(doc[f]), pa.array(uid[f]), pa.array(start[f].astype(np.int32)), pa.array((start[t] + window).astype(np.int32))], names=[*KEY, "start", "stop"])

    return run


def merged_spans(spans: list[dict] | None) -> list[tuple[int, int]]:
    """Spans (start, stop) in order, those that touch or overlap as one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted((s["start"], s["stop"]) for s in spans or []):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return out


CUT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, n_repeated_words long, n_word_spans long, spans array<struct<start:int,stop:int>>"
KINDS = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))]


def _cut(batches):
    for batch in batches:
        rows = []
        for doc, text, spans, by_word in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), batch.column("bytes"), batch.column("words")):
            raw = (text or "").encode()
            gone, told = merged_spans(spans.as_py()), merged_spans(by_word.as_py())
            digest, at = hashlib.sha256(), 0
            for a, b in gone:
                digest.update(raw[at:a])
                at = b
            digest.update(raw[at:])
            rows.append((doc, len(raw), sum(b - a for a, b in gone), len(gone), digest.hexdigest(), sum(b - a for a, b in told), len(told), [{"start": a, "stop": b} for a, b in gone]))
        names = [c.split()[0] for c in CUT.split(", ")]
        columns = list(zip(*rows)) or [[]] * len(names)
        yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, KINDS)], names=names)


def _some(docs: DataFrame, listed: DataFrame, how: str) -> DataFrame | None:
    """Rows of docs whose key is listed (left_semi) or is not (left_anti), found by a broadcast of keys before texts are shuffled; beyond BROADCAST_IDS all rows, or None."""
    if listed.count() > BROADCAST_IDS:
        return docs if how == "left_semi" else None
    return docs.join(F.broadcast(listed.select(KEY)), KEY, how)


def keyed(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) with the key of each text; a null doc_id counts as the least number there is."""
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)).cast("long"))
    return docs.select("doc_id", "text", doc.alias("doc"), F.xxhash64("text").alias("uid"))


def repeated_spans(docs: DataFrame, depth: Depth = BYTES) -> DataFrame:
    """(doc, uid, spans): units covered by windows that start anywhere else too; docs: rows with a key and a text.

    Rows with one key must have equal texts; each counts as a text of its own. Spans may overlap. A text
    shorter than the window, empty or null has no row, nor has one without repeats.
    """
    scratch = Scratch(docs.sparkSession)
    window = depth.window
    runs = scratch.written(docs.select(*KEY, "text").mapInArrow(_runs(depth), RUNS), "repeats-runs")
    # second digit: runs that occur again are repeated as a whole; first digit: grams that one run has are done
    by_run = runs.groupBy("digit", "run").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct(*KEY)).alias("first"))
    by_run = scratch.written(by_run, "repeats-by-run")
    by_digit = by_run.groupBy("digit").agg(F.count(F.lit(1)).alias("kinds"), F.sum("n").alias("_n")).where("_n > 1").drop("_n")
    left = scratch.written(by_run.join(by_digit, "digit"), "repeats-left")
    kept = scratch.written(runs.join(left, ["digit", "run"]), "repeats-kept")
    whole = kept.where("n > 1").select(*KEY, "start", (F.col("start") + F.col("size") + window - 1).alias("stop"))
    # what stays open: runs under a gram that other runs have; repeated ones stand in once, for comparison
    mixed = kept.where(F.expr("kinds > 1 and (n = 1 or (doc = first.doc and uid = first.uid))"))
    entry = F.struct("start", "size", "rel", "digit", (F.col("kinds") > HOT_KINDS).cast("int").alias("hot"))
    open_runs = mixed.select(*KEY, entry.alias("r"), "size")
    total = open_runs.agg(F.sum("size").alias("n")).first()["n"] or 0
    width = max(shuffle_width(docs.sparkSession), total * 9 // GROUP_BYTES + 1)
    per_doc = scratch.written(open_runs.groupBy(*KEY).agg(F.collect_set("r").alias("runs")), "repeats-open")
    texts = _some(docs.select(*KEY, "text"), per_doc, "left_semi").join(per_doc.hint("shuffle_hash"), KEY)
    dealt = texts.mapInArrow(_open_windows(depth, 2 * width), "part int, pieces binary, hashes binary")
    single = dealt.repartition(width, "part").mapInArrow(_repeated_windows(window), SPANS)
    spans = scratch.written(whole.unionByName(single), "repeats-spans")
    out = written(spans.groupBy(*KEY).agg(F.collect_set(F.struct("start", "stop")).alias("spans")), f"repeats-{depth.unit}")
    scratch.clear()
    return out


def remove_repeats(docs: DataFrame, depth: Depth = BYTES, told: Depth = WORDS) -> DataFrame:
    """One row for each row of docs (doc_id, text): bytes, removed bytes, removed runs, digest of what is kept, words in repeated passages and their runs, and the byte spans removed.

    Bytes under repeated windows of depth are removed. Repeated passages by words (told: blank-separated, case kept)
    are counted only: 50 words are often fewer than 400 bytes. Null texts are empty, repeated rows are repeats of
    each other, null doc_ids stay null, an empty table gives an empty one; other columns are not looked at.
    """
    keys = keyed(docs)
    cut, counted = (repeated_spans(keys, d).withColumnRenamed("spans", name) for d, name in ((depth, "bytes"), (told, "words")))
    per_doc = written(cut.join(counted, KEY, "full"), "repeats-per-doc")
    none, some = _some(keys, per_doc, "left_anti"), _some(keys, per_doc, "left_semi")
    joined = some.join(per_doc.hint("shuffle_hash"), KEY, "left").select("doc_id", "text", "bytes", "words")
    if none is not None:
        empty = F.lit(None).cast(per_doc.schema["bytes"].dataType)
        joined = joined.unionByName(none.select("doc_id", "text", empty.alias("bytes"), empty.alias("words")))
    return joined.mapInArrow(_cut, CUT)


def op9_radix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("spans")


QUERIES = {"op9_radix_repeats": op9_radix_repeats}
ORACLES: dict[str, str] = {}
