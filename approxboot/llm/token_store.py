"""Token ids in a compressed block format with random access.

Documents are range-partitioned by doc_id, encoded, and stored in blocks of at most BLOCK ids (or one
document). Re-Pair compresses each block: the most frequent pairs of adjacent symbols become nonterminals,
pass after pass; rules, the lengths they expand to and the documents' symbol and id counts are stored
beside the sequence, so any range of a document can be read without decoding the block.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import shuffle_width, table, written
from approxboot.llm.encoding import encoder, ragged, slices

BLOCK = 1 << 20
#: Ids of words that a worker remembers: about 170 MB with their texts.
CACHED_IDS = 8_000_000
#: Magic, version, first nonterminal, rules, documents, symbols, bytes of a symbol.
HEADER = struct.Struct("<4sHIIIIB")
MAGIC = b"RPB1"


def repair(ids: np.ndarray, last: np.ndarray, first_symbol: int, passes: int = 4, per_pass: int = 2048, least: int = 32) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Re-Pair over ids: (symbols, rules, last of the symbols).

    A pass counts all adjacent pairs, takes the most frequent ones of which none can overlap another (no
    symbol opens one and closes another), and replaces them all, from left to right within runs of a
    doubled symbol. Pairs never cross the end of a document (last). Stops below least occurrences.
    """
    # half the key for each symbol: 32-bit keys sort much faster, and most vocabularies fit
    half, kind = (16, np.uint32) if first_symbol + passes * per_pass <= 1 << 16 else (32, np.uint64)
    seq, rules = ids.astype(kind), []
    for _ in range(passes):
        if len(seq) < 2:
            break
        keys = (seq[:-1] << kind(half)) | seq[1:]
        inside = ~last[:-1]
        ordered = np.sort(keys[inside])
        if not len(ordered):
            break
        cuts = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
        sizes = np.diff(np.concatenate([cuts, [len(ordered)]]))
        often = np.flatnonzero(sizes >= least)
        often = often[np.argsort(-sizes[often], kind="stable")][: 4 * per_pass]
        opens, closes, chosen = set(), set(), []
        for key in ordered[cuts[often]].tolist():
            a, b = key >> half, key & ((1 << half) - 1)
            if a in closes or b in opens or (a == b and a in opens):
                continue
            opens.add(a)
            closes.add(b)
            chosen.append(key)
            if len(chosen) == per_pass:
                break
        if not chosen:
            break
        base = first_symbol + len(rules)
        picked = np.array(chosen, kind)
        order = np.argsort(picked)
        sorted_keys = picked[order]
        # a table of 2**16 hashes leaves few positions that are no match
        table, spread = np.zeros(1 << 16, bool), kind(0x9E3779B1 if half == 16 else 0x9E3779B97F4A7C15)
        table[(picked * spread) >> kind(2 * half - 16)] = True
        maybe = np.flatnonzero(table[(keys * spread) >> kind(2 * half - 16)] & inside)
        slot = np.minimum(np.searchsorted(sorted_keys, keys[maybe]), len(sorted_keys) - 1)
        match = sorted_keys[slot] == keys[maybe]
        at, number = maybe[match], order[slot[match]]
        if len(at):
            # matches side by side are runs of a doubled symbol: every other one counts
            breaks = np.concatenate([[True], np.diff(at) > 1])
            run_start = np.maximum.accumulate(np.where(breaks, np.arange(len(at)), 0))
            even = (np.arange(len(at)) - run_start) % 2 == 0
            at, number = at[even], number[even]
        seq[at] = (base + number).astype(kind)
        last = last.copy()
        last[at] = last[at + 1]
        keep = np.ones(len(seq), bool)
        keep[at + 1] = False
        seq, last = seq[keep], last[keep]
        rules += [(k >> half, k & ((1 << half) - 1)) for k in chosen]
    return seq, np.array(rules, np.int64).reshape(-1, 2), last


def rule_lengths(rules: np.ndarray, first_symbol: int) -> np.ndarray:
    """Ids that each nonterminal expands to; rules only use earlier ones."""
    out = [1] * len(rules)
    for i, (a, b) in enumerate(rules.tolist()):
        out[i] = (out[a - first_symbol] if a >= first_symbol else 1) + (out[b - first_symbol] if b >= first_symbol else 1)
    return np.array(out, np.int64)


def pack_block(ids: np.ndarray, doc_lengths: np.ndarray, first_symbol: int) -> bytes:
    """A block: header, rules, their expansion lengths, ids and symbols of each document, symbols."""
    last = np.zeros(len(ids), bool)
    ends = np.cumsum(doc_lengths)
    last[ends[doc_lengths > 0] - 1] = True
    seq, rules, seq_last = repair(ids, last, first_symbol)
    lengths = rule_lengths(rules, first_symbol)
    # every document holds one id at least, so it closes one symbol
    doc_symbols = np.diff(np.concatenate([[-1], np.flatnonzero(seq_last)]))
    width = 2 if first_symbol + len(rules) <= 1 << 16 else 4
    head = HEADER.pack(MAGIC, 1, first_symbol, len(rules), len(doc_lengths), len(seq), width)
    return b"".join([head, rules.astype("<u4").tobytes(), lengths.astype("<u4").tobytes(), doc_lengths.astype("<u4").tobytes(), doc_symbols.astype("<u4").tobytes(), seq.astype(f"<u{width}").tobytes()])


class Block:
    """A block opened for reading."""

    def __init__(self, data: bytes):
        magic, version, self.first, rules, docs, symbols, width = HEADER.unpack_from(data)
        if magic != MAGIC or version != 1:
            raise ValueError("not a token block")
        at = HEADER.size

        def take(n: int, kind: str) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(data, kind, n, at)
            at += out.nbytes
            return out

        self.rules = take(2 * rules, "<u4").reshape(-1, 2)
        self.lengths = take(rules, "<u4").astype(np.int64)
        self.doc_lengths = take(docs, "<u4").astype(np.int64)
        self.doc_symbols = take(docs, "<u4").astype(np.int64)
        self.symbols = take(symbols, f"<u{width}")

    def _tables(self) -> tuple[np.ndarray, np.ndarray]:
        """All expansions one after another (terminals expand to themselves), and where each nonterminal's starts."""
        starts = np.cumsum(self.lengths) - self.lengths
        flat = np.zeros(int(self.lengths.sum()), np.uint32)
        for i, (a, b) in enumerate(self.rules.tolist()):
            at = starts[i]
            for x in (a, b):
                n = self.lengths[x - self.first] if x >= self.first else 1
                flat[at : at + n] = flat[starts[x - self.first] : starts[x - self.first] + n] if x >= self.first else x
                at += n
        return flat, starts

    def _expand(self, symbols: np.ndarray) -> np.ndarray:
        if not len(self.rules):
            return symbols.astype(np.uint32)
        flat, starts = self._tables()
        # one table for all symbols: terminals stand for themselves at the front
        source = np.concatenate([np.arange(self.first, dtype=np.uint32), flat])
        at = np.concatenate([np.arange(self.first), self.first + starts])
        size = np.concatenate([np.ones(self.first, np.int64), self.lengths])
        return ragged(source, at[symbols], size[symbols])

    def ids(self) -> np.ndarray:
        """All ids of the block."""
        return self._expand(self.symbols)

    def read(self, doc: int, start: int = 0, stop: int | None = None) -> np.ndarray:
        """Ids start to stop of document number doc: only the symbols that overlap the range are expanded."""
        lo = int(self.doc_symbols[:doc].sum())
        symbols = self.symbols[lo : lo + int(self.doc_symbols[doc])]
        stop = int(self.doc_lengths[doc]) if stop is None else stop
        size = np.ones(len(symbols), np.int64)
        deep = symbols >= self.first
        size[deep] = self.lengths[symbols[deep].astype(np.int64) - self.first]
        ends = np.cumsum(size)
        a, b = np.searchsorted(ends, start, "right"), np.searchsorted(ends, stop, "left") + 1
        skipped = int(ends[a - 1]) if a else 0
        return self._expand(symbols[a:b])[start - skipped : stop - skipped]


BLOCK_SCHEMA = "shard int, block int, start_in_shard long, n_tokens long, doc_ids array<long>, payload binary"


def _encode_shard(path: str, end_id: int, first_symbol: int):
    def run(batches):
        shard, block, start = TaskContext.get().partitionId(), 0, 0
        enc = encoder(path, " ", CACHED_IDS)
        held_ids, held_lengths, held_docs, size = [], [], [], 0

        def flush():
            nonlocal block, start, size
            ids = np.concatenate(held_ids)
            row = pa.RecordBatch.from_pydict(
                {
                    "shard": pa.array([shard], pa.int32()),
                    "block": pa.array([block], pa.int32()),
                    "start_in_shard": pa.array([start], pa.int64()),
                    "n_tokens": pa.array([len(ids)], pa.int64()),
                    "doc_ids": pa.array([list(held_docs)], pa.list_(pa.int64())),
                    "payload": pa.array([pack_block(ids, np.concatenate(held_lengths), first_symbol)], pa.binary()),
                }
            )
            block, start, size = block + 1, start + len(ids), 0
            for x in (held_ids, held_lengths, held_docs):
                x.clear()
            return row

        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            docs = batch.column("doc_id").to_pylist()
            for lo, hi in slices(texts):
                ids, lengths = enc.encode(texts[lo:hi])
                out = np.full(len(ids) + len(lengths), end_id, np.uint32)
                ends = np.cumsum(lengths + 1)
                keep = np.ones(len(out), bool)
                keep[ends - 1] = False
                out[keep] = ids
                first, begun = 0, 0
                for i, end in enumerate(ends.tolist()):
                    if size and size + end - begun > BLOCK:
                        if i > first:
                            held_ids.append(out[int(ends[first - 1]) if first else 0 : begun])
                            held_lengths.append(lengths[first:i] + 1)
                            held_docs.extend(docs[lo + first : lo + i])
                            first = i
                        yield flush()
                    size += end - begun
                    begun = end
                held_ids.append(out[int(ends[first - 1]) if first else 0 :])
                held_lengths.append(lengths[first:] + 1)
                held_docs.extend(docs[lo + first : hi])
        if held_docs:
            yield flush()

    return run


def write_tokens(docs: DataFrame, tokenizer_path: str, end_id: int, vocabulary: int, shards: int | None = None) -> DataFrame:
    """Encode docs (doc_id, text) into blocks in the shared folder, in ascending doc_id order, and return the table of blocks.

    Ties of doc_id are ordered by a hash of the text; null ids come first; a null text is empty and holds
    the end id only. The range of ids of one shard is one task; a very frequent id is split by the hash.
    """
    spark = docs.sparkSession
    n = shards or shuffle_width(spark)
    keyed = docs.select("doc_id", "text", F.xxhash64("text").alias("_c"))
    ranged = keyed.repartitionByRange(n, "doc_id", "_c").sortWithinPartitions("doc_id", "_c").select("doc_id", "text")
    return written(ranged.mapInArrow(_encode_shard(tokenizer_path, end_id, vocabulary), BLOCK_SCHEMA), "tokens")


def _decode(batches):
    for batch in batches:
        for shard, block, base, docs, payload in zip(*[batch.column(c).to_pylist() for c in ("shard", "block", "start_in_shard", "doc_ids")], batch.column("payload")):
            opened = Block(payload.as_py())
            ids = opened.ids().astype("<u4")
            ends = np.cumsum(opened.doc_lengths)
            starts = ends - opened.doc_lengths
            view = memoryview(ids).cast("B")
            sums = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist())]
            yield pa.RecordBatch.from_pydict(
                {
                    "shard": pa.array([shard] * len(docs), pa.int32()),
                    "doc_id": pa.array(docs, pa.int64()),
                    "start": pa.array(base + starts, pa.int64()),
                    "n_tokens": pa.array(opened.doc_lengths, pa.int64()),
                    "ids_crc32": pa.array(sums, pa.int64()),
                }
            )


def read_digests(blocks: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every stored document, from the decoded blocks.

    Shards follow one another; the totals that offsets come from are one row for each shard.
    """
    sizes = blocks.groupBy("shard").agg(F.sum("n_tokens").alias("_n"))
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("shard", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    decoded = blocks.mapInArrow(_decode, "shard int, doc_id long, start long, n_tokens long, ids_crc32 long")
    # one row for each shard, and shards are as many as partitions
    joined = decoded.join(F.broadcast(offsets), "shard")
    return joined.select("doc_id", (F.col("start") + F.col("_before")).alias("start"), "n_tokens", "ids_crc32")


def op3_repair_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents written as grammar-compressed ids and read back. A null or empty text is the end id alone; rows with one doc_id, or a null one, are documents of their own."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return read_digests(write_tokens(docs, public_tokenizers.path("byte_bpe_50k.json"), 2, 50257))


QUERIES = {"op3_repair_tokens": op3_repair_tokens}
ORACLES: dict[str, str] = {}
