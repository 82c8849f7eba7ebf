"""Exact Jaccard self-join of shingle sets in the metric space of Jaccard distance.

Two sets at distance eps at most share one of their first shingles under any fixed order of all shingles:
their anchors. The sets that hold an anchor are a region around a pivot, the region's smallest node; a set
with several anchors lies in several regions, which is how sets near a border are replicated. A first round
measures every set's distance to pivots. Inside a region only sets of different components remain to be
compared, and the triangle inequality leaves those whose distances to the pivot differ by eps at most; they
are joined with further pivots of the region, recursively, until no region holds two components that have
not been compared. Rare shingles come first in the order, by a count sketch of all documents.

Nodes are distinct sets, named by 64-bit fingerprints; shingles are 64-bit hashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import connected_components, shuffle_width, table, written
from approxboot.llm.kernels import byte_slices, mix, shingle_sets, utf8

#: Share of the union, in percent, from which two documents link.
PERCENT = 75
SKETCH_BITS = 22
SKETCH_BLOCK = 4096
#: Regions up to this size are compared whole: a few pairs for each member.
SMALL_REGION = 16
#: Pivots that a larger region compares in its first rounds, by node: they join most of what belongs together.
PIVOTS = [4, 16]
#: Pivots of later rounds, members of the region's smallest components first: what is left to compare is theirs.
LATE_PIVOTS = 1024
#: Holders of one anchor that one task groups, about; those of commoner anchors are dealt over several.
SPLIT_HOLDERS = 20_000
#: Ids of documents that are broadcast at most: 16 bytes each.
BROADCAST_IDS = 1_000_000
#: Bytes of anchors that one task groups.
GROUP_BYTES = 32 << 20


def fingerprint(hashes: np.ndarray) -> int:
    """Order-free name of a set, as a signed 64-bit number."""
    with np.errstate(over="ignore"):
        s = mix(hashes + np.uint64(len(hashes)))
        both = np.array([s.sum(dtype=np.uint64), np.bitwise_xor.reduce(s)], np.uint64)
        return int(mix(both[:1] + mix(both[1:] ^ np.uint64(0xA5A5A5A5A5A5A5A5))).view(np.int64)[0])


def parity_bits(s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A bit for each of 2 to 4 times as many buckets as s has elements, whether the bucket's count is odd; and the same for half as many buckets."""
    w = 1 << max(7, (2 * len(s) - 1).bit_length())
    odd = (np.bincount((s & np.uint64(w - 1)).astype(np.int64), minlength=w) & 1).astype(bool)
    bits = np.packbits(odd, bitorder="little").view(np.int64)
    return bits, bits[: len(bits) // 2] ^ bits[len(bits) // 2 :]


def may_link(x: Column, xh: Column, y: Column, yh: Column, sizes: Column, percent: int) -> Column:
    """Whether parity bits leave it open that two sets link: buckets that are odd in one only are elements that differ.

    Sets whose bits differ more than twofold in number differ too much in size.
    """
    n, m = F.size(x), F.size(y)
    count = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda t, c: t + c)
    differ = F.when(n == m, count(x, y)).when(n == 2 * m, count(xh, y)).when(m == 2 * n, count(x, yh)).otherwise(F.lit(1 << 30))
    return (100 + percent) * differ.cast("long") <= (100 - percent) * sizes


def _rows(batch, n: int):
    """(position in the batch, set) of every row."""
    column = batch.column("text")
    for lo, hi in byte_slices(column):
        for i, s in enumerate(shingle_sets(*utf8(column, lo, hi), n)):
            yield lo + i, s


def _describe(n: int):
    """Rows of documents (doc_id, n_shingles, node) and, at a task's end, its counts of shingles by bucket."""
    names = ["doc_id", "uid", "n_shingles", "node", "bits", "half", "block", "counts"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int32(), pa.binary()]

    def run(batches):
        counts = np.zeros(1 << SKETCH_BITS, np.uint32)
        for batch in batches:
            sizes, nodes, bits, halves, held = [], [], [], [], []
            for _, s in _rows(batch, n):
                sizes.append(len(s))
                nodes.append(fingerprint(s) if len(s) else None)
                both = parity_bits(s) if len(s) else (None, None)
                bits.append(both[0])
                halves.append(both[1])
                held.append(s)
                if len(held) == 400:
                    _count(counts, held)
            _count(counts, held)
            none = [None] * len(sizes)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), batch.column("uid"), *[pa.array(x, k) for x, k in zip((sizes, nodes, bits, halves, none, none), kinds[2:])]], names=names)
        for lo in range(0, len(counts), 64 * SKETCH_BLOCK):
            packed = [(b, _sparse(counts[b * SKETCH_BLOCK : (b + 1) * SKETCH_BLOCK])) for b in range(lo // SKETCH_BLOCK, lo // SKETCH_BLOCK + 64)]
            packed = [x for x in packed if x[1]]
            none = [None] * len(packed)
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip((*[none] * 6, [b for b, _ in packed], [c for _, c in packed]), kinds)], names=names)

    return run


def _count(counts: np.ndarray, held: list[np.ndarray]) -> None:
    """Count the shingles of held by bucket, and let them go."""
    if held:
        at, n = np.unique(np.concatenate(held) >> np.uint64(64 - SKETCH_BITS), return_counts=True)
        counts[at] += n.astype(np.uint32)
        held.clear()


def _sparse(counts: np.ndarray) -> bytes:
    at = np.flatnonzero(counts)
    return at.astype("<u2").tobytes() + counts[at].astype("<u4").tobytes()


def _dense(parts: list[bytes]) -> np.ndarray:
    out = np.zeros(SKETCH_BLOCK, np.uint64)
    for p in parts:
        n = len(p) // 6
        np.add.at(out, np.frombuffer(p, "<u2", n), np.frombuffer(p, "<u4", n, 2 * n).astype(np.uint64))
    return np.minimum(out, np.uint64(0xFFFFFFFF)).astype(np.uint32)


def _add_up(batches):
    """Sum the counts of each block within a task."""
    held: dict[int, list[bytes]] = {}
    for batch in batches:
        for b, c in zip(batch.column("block").to_pylist(), batch.column("counts").to_pylist()):
            held.setdefault(b, []).append(c)
            if len(held[b]) == 8:
                held[b] = [_sparse(_dense(held[b]))]
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([_sparse(_dense(c)) for c in held.values()], pa.binary())], names=["block", "counts"])


def commonness(described: DataFrame) -> tuple[np.ndarray, np.ndarray, int]:
    """Level of each bucket of shingles, by how common it is; how many tasks the holders of its shingles are dealt over; and the number of all shingles.

    As many counters as 2**SKETCH_BITS reach the driver, however large the input is. Levels only order
    shingles: whatever they are, the join's result is the same.
    """
    parts = described.where("block is not null").select("block", "counts")
    once = parts.repartition(shuffle_width(described.sparkSession), "block").mapInArrow(_add_up, "block int, counts binary")
    total = np.zeros(1 << SKETCH_BITS, np.uint64)
    for r in once.collect():
        total[r["block"] * SKETCH_BLOCK : (r["block"] + 1) * SKETCH_BLOCK] += _dense([bytes(r["counts"])])
    mean = float(total.mean())
    z = (total.astype(np.float64) - mean) / np.sqrt(mean + 1)
    # eighths of a deviation up to 12 of them, then steps of the logarithm: any monotone scale will do
    level = np.where(z <= 12, np.clip(8 * (z + 4), 0, 128), 128 + 4 * np.log2(np.maximum(z, 12) / 12))
    # what a bucket holds beyond its share of all shingles can be one shingle's
    splits = np.clip((total.astype(np.float64) - mean - 10 * np.sqrt(mean + 1)) // SPLIT_HOLDERS + 1, 1, 65_535)
    return np.minimum(np.ceil(level), 255).astype(np.uint8), splits.astype(np.uint16), int(total.sum())


def anchors(s: np.ndarray, levels: np.ndarray, percent: int) -> np.ndarray:
    """The shingles of set s of which a set at the threshold shares one with it, rare ones first."""
    n = len(s)
    take = n - -(-percent * n // 100) + 1
    return s[np.argsort(levels[s >> np.uint64(64 - SKETCH_BITS)], kind="stable")[:take]]


def _deal_anchors(n: int, held_levels, percent: int, parts: int):
    """Anchors of all rows as (part, payload): arrays of anchors, nodes and sizes that one part holds."""

    def flush(held):
        h = np.concatenate([x[0] for x in held])
        sizes = np.array([len(x[0]) for x in held])
        node = np.repeat(np.array([x[1] for x in held], np.int64), sizes)
        size = np.concatenate([x[2] for x in held]).astype(np.uint32)
        splits = held_levels.value[1][h >> np.uint64(64 - SKETCH_BITS)].astype(np.uint64)
        part = (mix(h + mix(node.view(np.uint64)) % splits) % np.uint64(parts)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        cuts = np.searchsorted(part[order], np.arange(parts + 1))
        rows = []
        for p in range(parts):
            at = order[cuts[p] : cuts[p + 1]]
            if len(at):
                rows.append((p, h[at].astype("<u8").tobytes() + node[at].astype("<i8").tobytes() + size[at].astype("<u4").tobytes()))
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["part", "payload"])

    def run(batches):
        held, count, seen = [], 0, set()
        for batch in batches:
            for _, s in _rows(batch, n):
                if not len(s):
                    continue
                node = fingerprint(s)
                if node in seen:  # a copy of a set that this flush has
                    continue
                seen.add(node)
                a = anchors(s, held_levels.value[0], percent)
                # of two sets that link, the smaller (both, if equal) shares one of its first mid anchors
                mid = len(s) - -(-2 * percent * len(s) // (100 + percent)) + 1
                held.append((a, node, 2 * len(s) + (np.arange(len(a)) < mid)))
                count += len(a)
                if count > 500_000:
                    yield flush(held)
                    held, count, seen = [], 0, set()
        if held:
            yield flush(held)

    return run


def _regions(percent: int, held_levels):
    """Group the anchors of a task: kind 0 rows (node, other) to compare first, kind 1 rows (region, node, size, pivot) of large regions, kind 2 rows (anchor, node, size) of anchors that other tasks hold too."""
    names = ["kind", "a", "b", "size", "pivot"]
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]

    def run(batches):
        h, node, size = [], [], []
        for batch in batches:
            for p in batch.column("payload"):
                data = p.as_buffer()
                n = data.size // 20
                h.append(np.frombuffer(data, "<u8", n))
                node.append(np.frombuffer(data, "<i8", n, 8 * n))
                size.append(np.frombuffer(data, "<u4", n, 16 * n))
        if not h:
            return
        h, node, size = np.concatenate(h), np.concatenate(node), np.concatenate(size).astype(np.int64)
        order = np.lexsort((node, h))
        h, node, size = h[order], node[order], size[order]
        new = np.concatenate([[True], (h[1:] != h[:-1]) | (node[1:] != node[:-1])])
        h, node, size = h[new], node[new], size[new]
        mid, size = size % 2 == 1, size // 2
        first = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
        count = np.diff(np.concatenate([first, [len(h)]]))
        members, place = np.repeat(count, count), np.arange(len(h)) - np.repeat(first, count)
        found = []
        for step in range(1, SMALL_REGION):
            # every member of a small region with the one step places on; in larger ones with the pivot
            x = np.flatnonzero((members <= SMALL_REGION) & (place + step < members))
            if len(x):
                found.append((x, x + step))
        x = np.flatnonzero((members > SMALL_REGION) & (place > 0))
        found.append((x, x - place[x]))
        x, y = (np.concatenate([f[i] for f in found]) for i in range(2))
        near = 100 * np.minimum(size[x], size[y]) >= percent * np.maximum(size[x], size[y])
        near &= (mid[x] | (size[x] > size[y])) & (mid[y] | (size[y] > size[x]))
        x, y = node[x[near]], node[y[near]]
        ab = np.unique(np.column_stack([np.maximum(x, y), np.minimum(x, y)]), axis=0)
        for lo in range(0, len(ab), 50_000):
            part = ab[lo : lo + 50_000]
            zero = np.zeros(len(part), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip((zero.astype(np.int32), part[:, 0], part[:, 1], zero, zero), kinds)], names=names)
        seen = set()
        shared = held_levels.value[1][h[first] >> np.uint64(64 - SKETCH_BITS)] > 1
        for f, c in zip(first[shared].tolist(), count[shared].tolist()):
            name = int(mix(h[f : f + 1]).view(np.int64)[0])
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip((np.full(c, 2, np.int32), np.full(c, name), node[f : f + c], size[f : f + c], np.zeros(c, np.int64)), kinds)], names=names)
        large = (count > SMALL_REGION) & ~shared
        for f, c in zip(first[large].tolist(), count[large].tolist()):
            members = node[f : f + c]
            with np.errstate(over="ignore"):
                name = int(mix(np.array([mix(members.view(np.uint64)).sum(dtype=np.uint64)], np.uint64) + np.uint64(c)).view(np.int64)[0])
            if name in seen:
                continue
            seen.add(name)
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip((np.ones(c, np.int32), np.full(c, name), members, size[f : f + c], np.full(c, members[0])), kinds)], names=names)

    return run


def _wanted_sets(n: int):
    """Sets of rows whose set is the node that is wanted of them."""

    def run(batches):
        for batch in batches:
            wanted = batch.column("node").to_pylist()
            nodes, sets = [], []
            for i, s in _rows(batch, n):
                if len(s) and fingerprint(s) == wanted[i]:
                    nodes.append(wanted[i])
                    sets.append(s.view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(sets, pa.list_(pa.int64()))], names=["node", "hashes"])

    return run


class _Space:
    """The nodes of a join: their bits for a first look, and their sets, made from texts where they are needed."""

    def __init__(self, docs: DataFrame, nodes: DataFrame, percent: int, shingle: int):
        self.docs, self.nodes, self.percent, self.shingle = docs, nodes, percent, shingle

    def sides(self, df: DataFrame, node: str, tag: str) -> DataFrame:
        """df with the bits and size of the node in a column."""
        return df.join(self.nodes.select(F.col("node").alias(node), F.col("bits").alias(f"_{tag}"), F.col("half").alias(f"_{tag}h"), F.col("n_shingles").alias(f"_{tag}n")), node)

    def may_link(self) -> Column:
        return may_link(F.col("_x"), F.col("_xh"), F.col("_y"), F.col("_yh"), F.col("_xn") + F.col("_yn"), self.percent)

    def near(self, pairs: DataFrame) -> DataFrame:
        return self.sides(self.sides(pairs, "a", "x"), "b", "y").where(self.may_link()).select("a", "b")

    def sets(self, pairs: DataFrame) -> DataFrame:
        """(node, hashes) of the nodes in pairs. Few documents are looked for by broadcast, more than that by a shuffle."""
        wanted = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct()
        chosen = written(wanted.join(self.nodes.select("node", "doc_id"), "node"), "jaccard-wanted")
        small = chosen.count() <= BROADCAST_IDS
        held = F.broadcast(chosen) if small else chosen.hint("shuffle_hash")
        texts = self.docs.join(held, self.docs["doc_id"].eqNullSafe(chosen["doc_id"])).select("text", "node")
        made = texts.mapInArrow(_wanted_sets(self.shingle), "node long, hashes array<long>")
        return written(made.dropDuplicates(["node"]), "jaccard-hashes")

    def measured(self, pairs: DataFrame, near: bool = False) -> DataFrame:
        """Those of pairs (a, b) that may link, with their exact distance d. Large pivots are plain equi-join keys, which Spark splits."""
        pairs = written(pairs if near else self.near(pairs), "jaccard-near")
        sets = self.sets(pairs)
        one = pairs.join(sets.select(F.col("node").alias("b"), F.col("hashes").alias("_y")), "b")
        both = one.join(sets.select(F.col("node").alias("a"), F.col("hashes").alias("_x")), "a")
        common = F.size(F.array_intersect("_x", "_y"))
        out = both.select("a", "b", common.alias("_i"), (F.size("_x") + F.size("_y")).alias("_s"))
        link = 100 * F.col("_i") >= self.percent * (F.col("_s") - F.col("_i"))
        return written(out.select("a", "b", (1 - F.col("_i") / (F.col("_s") - F.col("_i"))).alias("d"), link.alias("link")), "jaccard-measured")


def _labelled(df: DataFrame, roots: DataFrame, column: str, out: str) -> DataFrame:
    named = roots.select(F.col("node").alias(column), F.col("root").alias("_root"))
    return df.join(named, column, "left").withColumn(out, F.coalesce("_root", column)).drop("_root")


def jaccard_components(docs: DataFrame, percent: int = PERCENT, shingle: int = 5) -> tuple[DataFrame, DataFrame]:
    """Similar documents among docs (doc_id, text).

    Returns (doc_id, n_shingles, component_id, root, uid) of every row, and links (a, b, d) between nodes that join
    up all components: pairs that are known to lie in one component already are not measured. Nulls and texts
    without words have no shingles and are alone in their component. Rows with equal sets are one node, whatever
    their number; component_id is the smallest doc_id of a component, or of equal sets; where all of those are
    null it is null. Rows with a null doc_id link like others. root names the component (null without words), uid
    is a hash of the text. Other columns are not looked at; an empty table gives no rows.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("uid"))
    described = written(docs.mapInArrow(_describe(shingle), "doc_id long, uid long, n_shingles long, node long, bits array<long>, half array<long>, block int, counts binary"), "jaccard-sets")
    rows = described.where("block is null").select("doc_id", "uid", "n_shingles", "node", "bits", "half")
    *levels, total = commonness(described)
    held = spark.sparkContext.broadcast(levels)
    width = max(shuffle_width(spark), total * 20 * (100 - percent) // 100 // GROUP_BYTES + 1)
    dealt = docs.select("text").mapInArrow(_deal_anchors(shingle, held, percent, 2 * width), "part int, payload binary")
    grouped = dealt.repartition(width, "part").mapInArrow(_regions(percent, held), "kind int, a long, b long, size long, pivot long")
    found = written(grouped, "jaccard-regions")
    pairs = written(found.where("kind = 0").select("a", "b").distinct(), "jaccard-pairs")
    # regions around one pivot overlap almost wholly: they are one
    regions = found.where("kind = 1").select(F.col("pivot").alias("region"), F.col("b").alias("node"), "size", "pivot").distinct()
    # an anchor that several tasks hold: its smallest node names the region; distances to that are not known
    parted = found.where("kind = 2").select("a", F.col("b").alias("node"), "size")
    parted = parted.join(parted.groupBy("a").agg(F.min("node").alias("region")), "a").select("region", "node", "size", F.lit(None).cast("long").alias("pivot")).distinct()
    regions = regions.unionByName(parted)

    nodes = rows.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.min("n_shingles").alias("n_shingles"), F.first("bits").alias("bits"), F.first("half").alias("half"))
    space = _Space(docs, written(nodes, "jaccard-nodes"), percent, shingle)

    # a set's smallest partner first; pairs that this already connects need no measuring
    smallest = pairs.groupBy("a").agg(F.min("b").alias("b"))
    measured = space.measured(smallest)
    links = measured.where("link").select("a", "b", "d")
    roots = written(connected_components(links), "jaccard-roots")
    rest = pairs.join(smallest, ["a", "b"], "left_anti")
    rest = _labelled(_labelled(rest, roots, "a", "_ra"), roots, "b", "_rb").where("_ra <> _rb").select("a", "b")
    more = space.measured(rest)
    links = links.unionByName(more.where("link").select("a", "b", "d"))
    roots = written(connected_components(links), "jaccard-roots")

    distances = measured.unionByName(more).select(F.col("a").alias("node"), F.col("b").alias("pivot"), "d")
    open_regions = regions.join(distances, ["node", "pivot"], "left")
    open_regions = open_regions.withColumn("d", F.when(F.col("node") == F.col("pivot"), F.lit(0.0)).otherwise(F.col("d"))).where("pivot is null or node <> pivot")
    eps, turn = 1 - percent / 100 + 1e-9, 0
    while True:
        named = _labelled(open_regions, roots, "node", "root")
        mixed = named.groupBy("region").agg(F.min("root").alias("_lo"), F.max("root").alias("_hi")).where("_lo <> _hi").select("region")
        named = written(named.join(mixed, "region", "left_semi"), "jaccard-open")
        if named.isEmpty():
            break
        most, order, ranked = (PIVOTS[turn], ["node"], named) if turn < len(PIVOTS) else (LATE_PIVOTS, ["_c", "node"], named.join(named.groupBy("region", "root").agg(F.count(F.lit(1)).alias("_c")), ["region", "root"]))
        rank = F.row_number().over(Window.partitionBy("region").orderBy(*order))
        pivots = ranked.withColumn("_k", rank).where(F.col("_k") <= most).select("region", F.col("node").alias("_p"), F.col("size").alias("_ps"), F.col("d").alias("_pd"), F.col("root").alias("_pr"))
        pivots = written(pivots, "jaccard-pivots")
        # the condition is part of the join: only pairs that may link become rows
        near = space.sides(named, "node", "x").join(space.sides(pivots, "_p", "y"), "region").where("root <> _pr and node <> _p").where(space.may_link())
        near = near.where(F.coalesce(F.abs(F.col("d") - F.col("_pd")) <= eps, F.lit(True)))
        pairs = near.select(F.greatest("node", "_p").alias("a"), F.least("node", "_p").alias("b")).distinct()
        measured = space.measured(pairs, near=True)
        fresh = measured.where("link").select("a", "b", "d")
        if not fresh.isEmpty():
            links = links.unionByName(fresh)
            # the roots so far stand for their components
            joined = roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(fresh.select("a", "b"))
            roots = written(connected_components(joined), "jaccard-roots")
        done, turn = pivots.select("region", F.col("_p").alias("node")), turn + 1
        open_regions = named.join(done, ["region", "node"], "left_anti").drop("root")

    node_doc = _labelled(space.nodes.select("node", "doc_id"), roots, "node", "root")
    least = node_doc.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    component = node_doc.join(least, "root").select("node", "component_id", "root")
    out = rows.join(component, "node", "left")
    return out.select("doc_id", "n_shingles", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "root", "uid"), links


def op2_jaccard_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets and components of all documents, by words of every whole text."""
    return jaccard_components(table(spark, sf_dir, "documents").select("doc_id", "text"))[0].select("doc_id", "n_shingles", "component_id")


QUERIES = {"op2_jaccard_regions": op2_jaccard_regions}
ORACLES: dict[str, str] = {}
