"""Benchmark passages in documents, within an edit distance.

Candidates come from a filter that loses nothing: an item is cut into pieces of a few characters, and since an
edit spoils one piece at most, a copy within the allowed edits still holds a known number of them, in places that
differ by no more than the edits. Stretches with that many pieces are aligned with the item with free ends.

The CGK embedding (a random walk over a string maps small edit distance to small Hamming distance) is kept as a
function. Hashes of it lose part of the copies near the allowed distance, so it decides nothing here.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.llm.common import table
from approxboot.llm.kernels import byte_slices, mix


@dataclass(frozen=True)
class Cgk:
    """distance: edits allowed, as a share of the item's length; gram: an item of fewer words is compared with nothing."""

    distance: float = 0.15
    gram: int = 3


def normalised(text: str) -> str:
    """Words in lower case with single blanks."""
    return " ".join(text.lower().split())


def cgk(strings: list[bytes], length: int, seed: int) -> np.ndarray:
    """Embeddings of strings, each 3 * length bytes (0 after a string's end), one row each; all walks share one random function."""
    steps = 3 * length
    rng = np.random.Generator(np.random.PCG64(seed))
    moves = rng.integers(0, 2, (steps, 256), dtype=np.uint8)
    padded = np.zeros((len(strings), steps + 1), np.uint8)
    for i, s in enumerate(strings):
        padded[i, : min(len(s), steps)] = np.frombuffer(s[:steps], np.uint8)
    at = np.zeros(len(strings), np.int64)
    rows = np.arange(len(strings))
    out = np.zeros((len(strings), steps), np.uint8)
    for t in range(steps):
        c = padded[rows, at]
        out[:, t] = c
        at += moves[t][c]
    return out


def edit_distance(a: str, b: str, most: int) -> int:
    """Levenshtein distance, or most + 1 where it is larger: bit-parallel over a column of b's characters."""
    if abs(len(a) - len(b)) > most:
        return most + 1
    if not a:
        return len(b)
    peq: dict[str, int] = {}
    for i, c in enumerate(a):
        peq[c] = peq.get(c, 0) | (1 << i)
    full, top = (1 << len(a)) - 1, 1 << (len(a) - 1)
    up, down, score = full, 0, len(a)
    for j, c in enumerate(b):
        eq = peq.get(c, 0)
        cross = eq | down
        flat = (((eq & up) + up) ^ up) | eq
        rise, fall = down | ~(flat | up) & full, up & flat
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
        if score - (len(b) - j - 1) > most:
            return most + 1
        rise, fall = (rise << 1) | 1, fall << 1
        up, down = (fall | ~(cross | rise)) & full, rise & cross & full
    return score


def _tables(text: str) -> tuple[int, dict[str, int]]:
    """Length of text, and the places of each of its characters as bits."""
    peq: dict[str, int] = {}
    for i, c in enumerate(text):
        peq[c] = peq.get(c, 0) | (1 << i)
    return len(text), peq


def _scores(tables: tuple[int, dict[str, int]], text: str, free: bool):
    """Distances of the whole of a tabled string to stretches of text that end after each of its characters, and start at 0 or (free) anywhere."""
    m, peq = tables
    full, top, first = (1 << m) - 1, 1 << (m - 1), 0 if free else 1
    up, down, score = full, 0, m
    for c in text:
        eq = peq.get(c, 0)
        cross = eq | down
        flat = (((eq & up) + up) ^ up) | eq
        rise, fall = down | ~(flat | up) & full, up & flat
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
        yield score
        rise, fall = (rise << 1) | first, fall << 1
        up, down = (fall | ~(cross | rise)) & full, rise & cross & full


def _grams(codes: np.ndarray, q: int) -> np.ndarray:
    """A hash of each q characters."""
    n = max(0, len(codes) - q + 1)
    out = np.zeros(n, np.uint64)
    for i in range(q):
        out = out * np.uint64(0x9E3779B97F4A7C15) + codes[i : i + n]
    return mix(out)


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)


class Items:
    """Benchmark items made ready: allowed edits, pieces by length, how many of them a copy holds, and tables for alignment."""

    def __init__(self, rows: list[tuple[int, str]], params: Cgk):
        self.ids = [i for i, _ in rows]
        self.texts = [normalised(t or "") for _, t in rows]
        self.most = np.array([int(params.distance * len(t)) for t in self.texts], np.int64)
        self.need = np.zeros(len(rows), np.int64)
        self.length = np.array([len(t) for t in self.texts], np.int64)
        found: dict[int, list] = {}
        for k, t in enumerate(self.texts):
            if len(t.split()) < params.gram:
                continue
            # the longest pieces of which all allowed edits leave one at least
            q = next((q for q in range(5, 0, -1) if len(t) // q > self.most[k]), 0)
            if not q:
                raise ValueError("distance must be less than the whole item")
            self.need[k] = len(t) // q - self.most[k]
            at = np.arange(0, len(t) - q + 1, q)
            found.setdefault(q, []).append((_grams(_codes(t), q)[at], np.full(len(at), k), at))
        self.pieces = {}
        for q, parts in found.items():
            grams, owner, place = (np.concatenate(x) for x in zip(*parts))
            order = np.argsort(grams, kind="stable")
            # most characters of a text are ruled out by one lookup
            screen = np.zeros(1 << 22, bool)
            screen[(grams >> np.uint64(42)).astype(np.int64)] = True
            kinds, first, count = np.unique(grams[order], return_index=True, return_counts=True)
            self.pieces[q] = kinds, first, count, owner[order], place[order], screen
        self.ahead = [_tables(t) for t in self.texts]
        self.back = [_tables(t[::-1]) for t in self.texts]


HITS = "doc_id long, item_id long, start int, stop int, distance int"


def _holds(key: np.ndarray, piece: np.ndarray, lo: int, hi: int, width: int, need: int) -> bool:
    """Whether need different pieces lie within width of one of the sorted keys lo to hi."""
    stop = int(np.searchsorted(key, key[hi] + width, "right"))
    keys, pieces = key[lo:stop].tolist(), piece[lo:stop].tolist()
    held: dict[int, int] = {}
    j = 0
    for i in range(hi - lo + 1):
        while j < len(keys) and keys[j] - keys[i] <= width:
            held[pieces[j]] = held.get(pieces[j], 0) + 1
            j += 1
        if len(held) >= need:
            return True
        held[pieces[i]] -= 1
        if not held[pieces[i]]:
            del held[pieces[i]]
    return False


def _stretches(items: Items, codes: np.ndarray) -> list[tuple[int, int, int]]:
    """(item, from, to): stretches of codes that hold every copy of an item within its edits."""
    out = []
    for q, (kinds, first, times, owner, place, screen) in items.pieces.items():
        seen = _grams(codes, q)
        maybe = np.flatnonzero(screen[(seen >> np.uint64(42)).astype(np.int64)])
        kind = np.minimum(np.searchsorted(kinds, seen[maybe]), len(kinds) - 1)
        real = kinds[kind] == seen[maybe]
        maybe, left, count = maybe[real], first[kind[real]], times[kind[real]]
        which = np.repeat(left - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
        # where the item would begin if this piece stood in its place; a copy's pieces differ there by twice the edits at most
        who, begin = owner[which], np.repeat(maybe, count) - place[which]
        if not len(who):
            continue
        # such places lie in one or two neighbouring strips; strips that share a counter only let more through
        strip, far = 2 * int(items.most.max()) + 1, int(items.length.max())
        strips = (len(codes) + far) // strip + 3
        spot = who * strips + (begin + far) // strip
        width = 1 << min(22, (len(items.ids) * strips).bit_length())
        spot &= width - 1
        met = np.bincount(spot, minlength=width)
        beside = np.maximum(np.roll(met, 1), np.roll(met, -1))
        keep = np.flatnonzero((met + beside)[spot] >= items.need[who])
        which, who, begin = which[keep], who[keep], begin[keep]
        key = (who << 40) + (1 << 39) + begin
        order = np.argsort(key)
        key, piece = key[order], place[which[order]]
        who = key >> 40
        last = np.arange(len(key)) + items.need[who] - 1
        good = np.flatnonzero(last < len(key))
        good = good[key[last[good]] - key[good] <= 2 * items.most[who[good]]]
        if not len(good):
            continue
        k, most = who[good], items.most[who[good]]
        begin = (key[good] & ((1 << 40) - 1)) - (1 << 39) - most
        end = (key[last[good]] & ((1 << 40) - 1)) - (1 << 39) + items.length[k] + 2 * most
        opens = np.concatenate([[True], (k[1:] != k[:-1]) | (begin[1:] > end[:-1])])
        heads = np.flatnonzero(opens)
        tails = np.append(heads[1:], len(good)) - 1
        for x, y, to in zip(heads.tolist(), tails.tolist(), np.maximum.reduceat(end, heads).tolist()):
            if _holds(key, piece, int(good[x]), int(good[y]), 2 * int(most[x]), int(items.need[k[x]])):
                out.append((int(k[x]), int(begin[x]), to))
    return out


def _aligned(items: Items, k: int, text: str, lo: int, hi: int) -> tuple[int, int, int] | None:
    """(distance, start, stop) of the closest stretch of text[lo:hi] to item k, by characters, within its edits."""
    least, stop = int(items.most[k]) + 1, -1
    at = text.find(items.texts[k], lo, hi)
    if at >= 0:
        return 0, at, at + len(items.texts[k])
    for j, d in enumerate(_scores(items.ahead[k], text[lo:hi], True), lo + 1):
        if d < least:
            least, stop = d, j
    if stop < 0:
        return None
    before = text[max(0, stop - int(items.length[k]) - least) : stop][::-1]
    start = stop - next(j for j, d in enumerate(_scores(items.back[k], before, False), 1) if d == least)
    return least, start, stop


def _bytes(raw: str, text: str, start: int, stop: int) -> tuple[int, int]:
    """The words of raw that text[start:stop] touches, in UTF-8 bytes from raw's first word; text is raw, normalised."""
    start += text[start] == " "
    stop -= text[stop - 1] == " "
    spans = [m.span() for m in re.finditer(r"\S+", raw)]
    places = spans[text.count(" ", 0, start)][0], spans[text.count(" ", 0, stop - 1)][1]
    return tuple(len(raw[spans[0][0] : x].encode("utf-8", "surrogatepass")) for x in places)


def _batch_hits(items: Items, column) -> list[tuple[int, int, int, int, int]]:
    """(row, item, start, stop, distance) of a column of texts."""
    out = []
    for lo, hi in byte_slices(column):
        raw = [t or "" for t in column.slice(lo, hi - lo).to_pylist()]
        texts = [normalised(t) for t in raw]
        begin = np.cumsum([0] + [len(t) + 1 for t in texts])
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        for k, a, b in _stretches(items, _codes("\n".join(texts))):
            for r in range(max(0, int(np.searchsorted(begin, a, "right")) - 1), len(texts)):
                if begin[r] >= b:
                    break
                at = int(begin[r])
                got = _aligned(items, k, texts[r], max(0, a - at), min(len(texts[r]), b - at))
                if got and ((r, k) not in best or got < best[r, k]):
                    best[r, k] = got
        out += [(lo + r, items.ids[k], *_bytes(raw[r], texts[r], a, b), d) for (r, k), (d, a, b) in sorted(best.items())]
    return out


def _search(held):
    def run(batches):
        for batch in batches:
            docs = batch.column("doc_id").to_pylist()
            hits = [(docs[r], *rest) for r, *rest in _batch_hits(held.value, batch.column("text"))]
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()]
            columns = list(zip(*hits)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, kinds)], names=["doc_id", "item_id", "start", "stop", "distance"])

    return run


def _without_hits(held, text: str):
    def run(batches):
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            keep[[h[0] for h in _batch_hits(held.value, batch.column(text))]] = False
            yield batch.filter(pa.array(keep))

    return run


#: Bytes of benchmark text that one search holds; beyond that the benchmark is searched in blocks.
ITEM_BYTES = 32 << 20


def _blocks(benchmark: DataFrame, params: Cgk):
    """The benchmark's items, made ready and broadcast, in blocks whose size was measured."""
    spark = benchmark.sparkSession
    sized = benchmark.where("text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text")
    total = sized.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    blocks = total // ITEM_BYTES + 1
    for b in range(blocks):
        part = sized.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        rows = sorted((-1 if r["item_id"] is None else r["item_id"], r["text"]) for r in part.collect())
        yield spark.sparkContext.broadcast(Items(rows, params))


def contaminated(docs: DataFrame, benchmark: DataFrame, params: Cgk = Cgk()) -> DataFrame:
    """(doc_id, item_id, start, stop, distance): the closest place of each benchmark item in each document that has it.

    docs: (doc_id, text), benchmark: (item_id, text). start and stop count UTF-8 bytes from the document's
    first word. Items of fewer words than a gram are compared with nothing; null texts hold nothing; a null
    item_id is given as -1. Rows of docs with one doc_id are searched each. A benchmark beyond ITEM_BYTES
    is searched block by block.
    """
    slim, out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), None
    for held in _blocks(benchmark, params):
        found = slim.mapInArrow(_search(held), HITS)
        out = found if out is None else out.unionByName(found)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, params: Cgk = Cgk(), text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that hold no benchmark item; each is judged by itself, without a shuffle."""
    for held in _blocks(benchmark, params):
        docs = docs.mapInArrow(_without_hits(held, text), docs.schema)
    return docs


def op8_cgk_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents against all benchmark items; a document without an item has no row."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return contaminated(docs, table(spark, sf_dir, "benchmark"))


QUERIES = {"op8_cgk_decontamination": op8_cgk_decontamination}
ORACLES: dict[str, str] = {}
