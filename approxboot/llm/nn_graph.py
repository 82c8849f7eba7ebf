"""Near-duplicate embeddings by NN-descent.

A neighbour graph is refined round by round: the members of a vector's list, and those that list it, meet at that
vector and are compared with each other there. Lists start from hyperplane signatures, and grow where they are
full of links. The descent only has to find which vectors belong to one component: links within a component are
then counted by comparing all its vectors, block by block, so lists that are full lose none. Whether components
are whole is audited against a brute-force search for a sample of vectors: a miss adds signatures and another
descent, and where misses remain all vectors are compared.

Equal vectors are one node with a count, so a vector that a large part of all rows share costs one row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import connected_components, table, written

COSINE = 0.95

#: Share of the audited links that the descent has to hold within its components; with less, all vectors are compared.
RECALL = 1.0

#: Vectors of a block when the vectors of a component, or all of them, are compared.
COMPONENT_BLOCK, WHOLE_BLOCK = 512, 2048


def _unit(v: list | None) -> np.ndarray | None:
    """The vector over its norm, which is taken after scaling, so that no finite vector is too long or too short; None for what has no direction."""
    if not v or any(x is None for x in v):
        return None
    x = np.array(v, np.float64)
    longest = np.abs(x).max()
    if not np.isfinite(longest) or longest == 0:
        return None
    x = x / longest
    return x / np.sqrt((x * x).sum())


def _nodes(batches):
    """Rows (vec_id, node, unit) of usable vectors: node names the exact direction's bytes, unit is the vector over its norm."""
    import hashlib

    for batch in batches:
        ids, names, units = [], [], []
        for i, v in zip(batch.column("vec_id").to_pylist(), batch.column("embedding").to_pylist()):
            unit = _unit(v)
            if unit is None:
                continue
            ids.append(i)
            names.append(int.from_bytes(hashlib.blake2b(np.array(v, np.float64).tobytes(), digest_size=8).digest(), "little", signed=True))
            units.append(unit)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(names, pa.int64()), pa.array([u.tolist() for u in units], pa.list_(pa.float64()))], names=["vec_id", "node", "unit"])


def _matrix(column) -> np.ndarray:
    """Vectors of one length as rows, without a Python object for each number."""
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _list_of(rows: np.ndarray) -> pa.Array:
    """Rows of a matrix as lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, rows.shape[1] or 1, dtype=np.int32)), pa.array(rows.ravel()))


def _signatures(tables: int, bits: int, seed: int, dims: int, whole: bool):
    """Rows (bucket, node) of each vector, with its unit if whole: a signature of hyperplane sides for each table."""

    def run(batches):
        planes = np.random.Generator(np.random.PCG64(seed)).standard_normal((tables * bits, dims))
        weights = 1 << np.arange(bits, dtype=np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            units = _matrix(batch.column("unit"))
            sides = (units @ planes.T > 0).reshape(len(units), tables, bits)
            code = (sides * weights).sum(2) + (np.arange(tables, dtype=np.int64) << 40)
            columns = [pa.array(code.ravel()), pa.array(np.repeat(batch.column("node").to_numpy(), tables))]
            yield pa.RecordBatch.from_arrays(columns + ([_list_of(np.repeat(units, tables, axis=0))] if whole else []), names=["bucket", "node", "unit"][: 2 + whole])

    return run


#: Candidates that a vector takes from one bucket, or from one meeting, at most; and rows of a bucket that stay together.
TAKEN, TOGETHER = 3, 4096
#: kind 0: other is a candidate for node's list; kind 1: node and other belong to one component.
FOUND = "kind int, node long, other long, cos double"


def _found(node, other, cos, joined) -> pa.RecordBatch:
    kind = np.repeat([0, 1], [len(node), len(joined[0])]).astype(np.int32)
    both = [np.concatenate(x) for x in zip((node, other, cos), joined)]
    return pa.RecordBatch.from_arrays([pa.array(kind), *map(pa.array, both)], names=["kind", "node", "other", "cos"])


def _along(reach: int, threshold: float):
    """Compare each row of a sorted stream (bucket, sub, node, unit) with the reach rows after it in its bucket."""

    def run(batches):
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            key = np.stack([batch.column(c).to_numpy() for c in ("bucket", "sub")], 1)
            node, x = batch.column("node").to_numpy(), _matrix(batch.column("unit"))
            if held is not None:
                key, node, x = (np.concatenate(p) for p in zip(held, (key, node, x)))
            n = len(node)
            near = np.full((n, 2 * reach), -2.0)
            for step in range(1, min(reach, n - 1) + 1):
                same = (key[step:] == key[:-step]).all(1) & (node[step:] != node[:-step])
                cos = np.where(same, (x[step:] * x[:-step]).sum(1), -2.0)
                near[:-step, step - 1] = cos
                near[step:, reach + step - 1] = cos
            shift = np.concatenate([np.arange(1, reach + 1), -np.arange(1, reach + 1)])
            best = np.argsort(-near, axis=1)[:, :TAKEN]
            cos = np.take_along_axis(near, best, 1).ravel()
            row, other = np.repeat(np.arange(n), best.shape[1]), (np.arange(n)[:, None] + shift[best]).ravel()
            real = cos > -2
            i, j = np.nonzero(near[:, :reach] >= threshold)
            yield _found(node[row[real]], node[other[real]], cos[real], (node[i], node[i + shift[j]], near[i, j]))
            held = tuple(p[-reach:] for p in (key, node, x))

    return run


def _meeting(threshold: float):
    """Compare the members (member, fresh, unit, worst) that meet at a node, in a stream sorted by node: pairs with a fresh one.

    A member takes what is nearer than the worst of its full list. What links is joined up.
    """

    def compare(members, fresh, units, worst):
        cos = units @ units.T
        np.fill_diagonal(cos, -2.0)
        cos[~(fresh[:, None] | fresh[None, :])] = -2.0
        near = cos >= threshold
        least, _ = _reached(near, members, members) if near.any() else (members, members)
        best = np.argsort(-cos, axis=1)[:, :TAKEN]
        value = np.take_along_axis(cos, best, 1)
        i, j = np.nonzero(value > np.maximum(worst, -1.5)[:, None])
        moved = np.flatnonzero(least != members)
        return members[i], members[best[i, j]], value[i, j], members[moved], least[moved], np.ones(len(moved))

    def run(batches):
        held, found = None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            part = [batch.column("node").to_numpy(), batch.column("member").to_numpy(), batch.column("fresh").to_numpy() > 0, _matrix(batch.column("unit")), batch.column("worst").to_numpy()]
            if held is not None:
                part = [np.concatenate(p) for p in zip(held, part)]
            cuts = np.flatnonzero(part[0][1:] != part[0][:-1]) + 1
            bounds = [0, *cuts.tolist()]
            for lo, hi in zip(bounds, bounds[1:]):
                if hi - lo > 1 and part[2][lo:hi].any():
                    found.append(compare(*(p[lo:hi] for p in part[1:])))
            held = [p[bounds[-1] :] for p in part]
            if found:
                x = [np.concatenate(c) for c in zip(*found)]
                yield _found(*x[:3], x[3:])
                found = []
        if held is not None and len(held[0]) > 1 and held[2].any():
            x = compare(*held[1:])
            yield _found(*x[:3], x[3:])

    return run


def _best(candidates: DataFrame, k: int, most: int, threshold: float) -> DataFrame:
    """Lists (node, other, cos): the k nearest of each node, and up to most that link."""
    one = candidates.repartition("node").groupBy("node", "other").agg(F.max("cos").alias("cos"))
    rank = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("cos"), "other"))
    ranked = one.withColumn("_k", rank).where(F.col("_k") <= most)
    return ranked.where((F.col("_k") <= k) | (F.col("cos") >= threshold)).select("node", "other", "cos")


def _audit(sample: np.ndarray, names: np.ndarray, threshold: float):
    """Pairs of a block of vectors with the sampled ones at the threshold or above, by brute force."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows or not len(sample):
                continue
            units = _matrix(batch.column("unit"))
            nodes = batch.column("node").to_numpy()
            i, j = np.nonzero(units @ sample.T >= threshold)
            own = nodes[i] != names[j]
            a, b = nodes[i][own], names[j][own]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])

    return run


def descend(vectors: DataFrame, threshold: float = COSINE, k: int = 10, tables: int = 24, bits: int = 12, reach: int = 8, rounds: int = 6, audit: int = 500, recall: float = RECALL, seed: int = 11) -> tuple[DataFrame, float]:
    """Edges (a, b) that join up vectors (node, unit) with cosines >= threshold, and the audited recall of their components.

    Lists hold k neighbours; one that is full of links holds twice as many in the next round, and four times in
    those after it. audit nodes, chosen by hash, are compared with all others by brute force: a query set of fixed
    size against all rows. The recall is the share of their links that lie within one component before these links
    become edges too. Below recall, more signatures are added and the graph descends again, three times at
    most; what the caller does with a lower one is its own matter.
    """
    spark = vectors.sparkSession
    edges, lists, got = None, None, 0.0
    first = vectors.select("unit").head()
    if first is None:
        return spark.createDataFrame([], "a long, b long"), 1.0
    dims = len(first["unit"])
    chosen = vectors.orderBy(F.xxhash64(F.lit(seed), "node"), "node").limit(audit).collect()
    sample, names = np.array([r["unit"] for r in chosen]), np.array([r["node"] for r in chosen], np.int64)
    truth = written(vectors.mapInArrow(_audit(sample, names, threshold), "a long, b long").distinct(), "nn-truth")
    for attempt in range(3):
        # a bucket that many vectors share is dealt into parts by their hash
        signed = vectors.mapInArrow(_signatures(tables, bits, seed + attempt, dims, False), "bucket long, node long")
        large = signed.groupBy("bucket").agg(F.ceil(F.count(F.lit(1)) / TOGETHER).alias("_n")).where("_n > 1")
        whole = vectors.mapInArrow(_signatures(tables, bits, seed + attempt, dims, True), "bucket long, node long, unit array<double>")
        order = F.xxhash64(F.lit(seed + attempt), "node", "bucket")
        dealt = whole.join(F.broadcast(written(large, "nn-large")), "bucket", "left").withColumn("_o", order).withColumn("sub", F.coalesce(F.pmod("_o", "_n"), F.lit(0)).cast("long"))
        met = dealt.select("bucket", "sub", "_o", "node", "unit").repartition("bucket", "sub").sortWithinPartitions("bucket", "sub", "_o")
        found = written(met.mapInArrow(_along(reach, threshold), FOUND), "nn-found")
        for turn in range(rounds + 1):
            joined = found.where("kind = 1").select(F.col("node").alias("a"), F.col("other").alias("b")).distinct()
            edges = joined if edges is None else edges.unionByName(joined)
            candidates = found.where("kind = 0").select("node", "other", "cos")
            before = lists
            lists = written(_best(candidates if lists is None else lists.unionByName(candidates), k, k << min(turn, 2), threshold), "nn-lists")
            if turn == rounds:
                break
            fresh = F.lit(1) if before is None else F.when(F.col("_was").isNull(), 1).otherwise(0)
            marked = lists if before is None else lists.join(before.select("node", "other", F.lit(1).alias("_was")), ["node", "other"], "left")
            marked = marked.select("node", "other", "cos", fresh.alias("fresh"))
            # who meets at a node: its list, and the nearest of those that list it
            turned = marked.select(F.col("other").alias("node"), F.col("node").alias("other"), "cos", "fresh")
            rank = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("cos"), "other"))
            turned = turned.withColumn("_k", rank).where(F.col("_k") <= k).drop("_k")
            members = marked.unionByName(turned).groupBy("node", F.col("other").alias("member")).agg(F.max("fresh").alias("fresh"))
            full = lists.groupBy("node").agg(F.when(F.count(F.lit(1)) >= k, F.min("cos")).otherwise(F.lit(-2.0)).alias("worst"))
            known = vectors.join(full, "node", "left").select(F.col("node").alias("member"), "unit", F.coalesce("worst", F.lit(-2.0)).alias("worst"))
            meeting = members.join(known, "member").select("node", "member", "fresh", "unit", "worst").repartition("node").sortWithinPartitions("node")
            found = written(meeting.mapInArrow(_meeting(threshold), FOUND), "nn-found")
            if found.where((F.col("kind") == 1) | (F.col("cos") >= threshold)).isEmpty():
                break
        edges = written(edges.distinct(), "nn-links")
        roots = written(connected_components(edges), "nn-roots")
        ends = truth.join(roots.select(F.col("node").alias("a"), F.col("root").alias("_r")), "a").join(roots.select(F.col("node").alias("b"), F.col("root").alias("_s")), "b")
        n = truth.count()
        got = ends.where("_r = _s").count() / n if n else 1.0
        if got >= recall:
            break
    return edges.unionByName(truth).distinct(), got


def _reached(near: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The smallest name that each row and each column of near reaches; x names the rows and y the columns."""
    top = np.iinfo(np.int64).max
    while True:
        rows = np.minimum(x, np.where(near, y, top).min(1))
        columns = np.minimum(y, np.where(near, rows[:, None], top).min(0))
        if np.array_equal(rows, x) and np.array_equal(columns, y):
            return rows, columns
        x, y = rows, columns


def _block_links(group: list, threshold: float, dims: int) -> list[np.ndarray]:
    """Columns node, links and least of the vectors of one pair of blocks that have links there."""
    group = pa.Table.from_batches(group)
    side, node, copies = (group.column(c).to_numpy() for c in ("side", "node", "copies"))
    units = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in group.column("unit").chunks]).reshape(-1, dims)
    one = group.column("p")[0] == group.column("q")[0]
    x = np.flatnonzero(side == 0)
    y = x if one else np.flatnonzero(side == 1)
    if not len(x) or not len(y):
        return []
    near = units[x] @ units[y].T >= threshold
    if one:
        np.fill_diagonal(near, False)
    share = near.astype(np.float64)
    rows, columns = _reached(near, node[x], node[y])
    out = [np.stack([node[x], (share @ copies[y]).astype(np.int64), rows])[:, near.any(1)]]
    if not one:
        out.append(np.stack([node[y], (copies[x] @ share).astype(np.int64), columns])[:, near.any(0)])
    return out


def _links(threshold: float, dims: int):
    """Rows (node, links, least) of pairs of blocks, which arrive one after the other."""

    def run(batches):
        group, open_ = [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(c).to_numpy() for c in ("root", "p", "q")], 1)
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(1)) + 1).tolist(), len(keys)]
            found = []
            for lo, hi in zip(cuts, cuts[1:]):
                if group and tuple(keys[lo]) != open_:
                    found += _block_links(group, threshold, dims)
                    group = []
                open_ = tuple(keys[lo])
                group.append(batch.slice(lo, hi - lo))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in np.concatenate(found, 1)], names=["node", "links", "least"])
        found = _block_links(group, threshold, dims) if group else []
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in np.concatenate(found, 1)], names=["node", "links", "least"])

    return run


def counted_links(vectors: DataFrame, threshold: float, block: int) -> DataFrame:
    """Links (node, links, least) of vectors (node, unit, copies, root), each compared with all others of its root.

    A root's vectors are dealt over blocks of about block vectors, and each pair of blocks is compared by one
    task, so no root is held in one task and no pair becomes a row. A node has a row for each pair of blocks
    where it has links: links counts them, least is a node of the same component.
    """
    first = vectors.select("unit").head()
    if first is None:
        return vectors.sparkSession.createDataFrame([], "node long, links long, least long")
    blocks = vectors.groupBy("root").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("_n")).where("root is not null")
    dealt = vectors.join(blocks, "root").withColumn("_i", F.pmod(F.xxhash64(F.lit(5), "node"), F.col("_n")).cast("int"))
    met = dealt.withColumn("_j", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    keyed = met.select("root", F.least("_i", "_j").alias("p"), F.greatest("_i", "_j").alias("q"), (F.col("_i") > F.col("_j")).cast("int").alias("side"), "node", "copies", "unit")
    ordered = keyed.repartition("root", "p", "q").sortWithinPartitions("root", "p", "q")
    return ordered.mapInArrow(_links(threshold, len(first["unit"])), "node long, links long, least long")


def near_duplicates(rows: DataFrame, threshold: float = COSINE, **options) -> tuple[DataFrame, float]:
    """(vec_id, n_links, component_id, kept) of every row of rows (vec_id, embedding), and the audited recall of the descent.

    n_links counts all links within a component. Where the descent's recall stays under the one asked for, all
    vectors are compared with each other, and the recall is 1.

    Vectors that are null, empty, zero or hold null or non-finite components have no links. Equal vectors
    link with each other. Rows with one vec_id count as vectors of their own. Vectors of different length
    must not occur together.
    """
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    usable = written(rows.mapInArrow(_nodes, "vec_id long, node long, unit array<double>"), "nn-rows")
    sizes = usable.groupBy("node").agg(F.count(F.lit(1)).alias("copies"), F.min("vec_id").alias("least"))
    vectors = written(usable.groupBy("node").agg(F.first("unit").alias("unit")), "nn-vectors")
    edges, recall = descend(vectors, threshold, **options)
    roots = written(connected_components(edges), "nn-roots")
    weighed = vectors.join(sizes.select("node", "copies"), "node")
    if recall >= options.get("recall", RECALL):
        found = written(counted_links(weighed.join(roots, "node"), threshold, COMPONENT_BLOCK), "nn-counts")
    else:
        found = written(counted_links(weighed.withColumn("root", F.lit(0).cast("long")), threshold, WHOLE_BLOCK), "nn-counts")
        roots, recall = connected_components(found, "node", "least"), 1.0
    linked = found.groupBy("node").agg(F.sum("links").alias("_l"))
    facts = sizes.join(linked, "node", "left").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    facts = written(facts.select("node", "root", "least", (F.coalesce("_l", F.lit(0)) + F.col("copies") - 1).alias("n_links")), "nn-facts")
    least = facts.groupBy("root").agg(F.min("least").alias("component_id"))
    named = facts.join(least, "root").select("node", "n_links", "component_id")
    good = usable.select("vec_id", "node").join(named, "node").select("vec_id", "n_links", "component_id")
    alone = rows.mapInArrow(_unusable, "vec_id long").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    out = good.unionByName(alone)
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True))), recall


def _unusable(batches):
    for batch in batches:
        ids = [i for i, v in zip(batch.column("vec_id").to_pylist(), batch.column("embedding").to_pylist()) if _unit(v) is None]
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64())], names=["vec_id"])


def op10_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All embeddings; the audited recall is 1, by the descent or by comparing all vectors, so nothing is left to return of it."""
    return near_duplicates(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))[0]


QUERIES = {"op10_nn_descent": op10_nn_descent}
ORACLES: dict[str, str] = {}
