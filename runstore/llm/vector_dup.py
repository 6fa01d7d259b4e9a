"""Operator 1: near-duplicate embeddings by NN-descent.

Vectors of one label (and one length) are compared by cosine in double
precision.  Vectors of equal bytes after scaling to length 1 are collapsed
first, with their count.  A neighbour graph of the best `k` per vector is then
refined:

1. start: `trees` random-projection codes put vectors into leaves (codes are
   taken about the label's mean, with as many bits as the label's size asks;
   larger leaves are split by hash), whose members are compared with each other;
2. descent: every vector passes its neighbours and reverse neighbours on to each
   other (neighbours of neighbours), pairs that were not met before are compared
   and lists keep the best k, until a round finds next to no new link or `rounds`
   are over.  Centres are dealt by the leaf that holds them, and a leaf gets each
   member's vector once, in half precision, however many of its centres share it;
3. saturated lists (all k within the threshold) are enlarged up to `most`
   entries at the threshold.  Vectors that fill `most` are compared with all of
   their label, in pairs of blocks that hand on numbers of links and connections
   instead of pairs, so a class of m vectors never becomes m^2 rows;
4. links of the other vectors are closed over two hops: neighbours of linked
   neighbours are compared until nothing is new; who reaches `most` joins 3;
5. audit: vectors chosen by hash (`audit` at first, up to 16 times as many until
   `seen` links are met) are compared with all of their labels, and the share of
   their links that was found is the recall.  Below `recall`, steps 1-4 run again
   with other leaves; if that is not enough either, all vectors go the way of 3,
   which is exhaustive.  The recall stands in the result.

Half precision only nominates: every pair counted as a link was confirmed in
double precision, by one sum of products, whichever step found it.  No task
holds more than a leaf with its members, or a pair of blocks.

Vectors that are null, empty, zero or hold null or non-finite components, and
those of null labels, link with nothing and have 0 links.  Rows with null ids
do the same; their component is null.  Of rows with one id and different
vectors, each counts as a vector of its own and all share a component.  Equal
cosines are no special case: a pair at the threshold is a link.  An empty table
gives no rows.  Other columns, whatever their names, are not read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from runstore.llm import base

THRESHOLD = 0.98
#: Vectors of a leaf, and of a block.
LEAF, BLOCK = 512, 2048
#: What half precision may lack in a cosine.
SLACK = 2e-3
#: Closer to the threshold than this, a product of matrices is summed again by `cosines`.
_NEAR = 1e-9


def _vectors(column, kind=np.float64) -> np.ndarray:
    """Binary column of numbers as a matrix (all of one length)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, 0), kind)
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(kind).reshape(len(column), -1)


def cosines(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Cosine of each row of x with that of y (unit vectors): the sum that decides."""
    return np.einsum("ij,ij->i", x, y)


def within(x: np.ndarray, y: np.ndarray, threshold: float) -> np.ndarray:
    """Matrix of booleans: which rows of x and y are linked."""
    s = x @ y.T
    out = s >= threshold
    i, j = np.nonzero(np.abs(s - threshold) < _NEAR)
    if len(i):
        out[i, j] = cosines(x[i], y[j]) >= threshold
    return out


def _grouped(fn: Callable, schema: pa.Schema):
    """mapInArrow over rows sorted by their first column: fn(rows of one value) -> columns."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        key = None

        def done() -> Iterator[pa.RecordBatch]:
            if held:
                out = fn(pa.Table.from_batches(held).combine_chunks())
                if out is not None:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema)], schema=schema)
                held.clear()

        for batch in batches:
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            if not len(keys):
                continue
            cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1), len(keys)]
            for a, b in zip(cuts, cuts[1:]):
                if key is None or keys[a] != key:
                    yield from done()
                    key = keys[a]
                held.append(batch.slice(a, b - a))
        yield from done()

    return run


def _by_key(df: DataFrame, key: str, fn: Callable, schema: str) -> DataFrame:
    kinds = {"long": pa.int64(), "double": pa.float64(), "int": pa.int32()}
    arrow = pa.schema([(n, kinds[t]) for n, t in (x.strip().split(" ") for x in schema.split(","))])
    rest = [c for c in df.columns if c != key]
    return df.select(key, *rest).repartition(key).sortWithinPartitions(key).mapInArrow(_grouped(fn, arrow), schema)


def normalised(rows: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    """Rows (vec_id, part, v, u) of vectors that may link: part is a hash of label and length, v the unit vector's bytes, u the same in half precision."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, parts, out, half = [], [], [], []
            for i, part, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                x = v.values.to_numpy(zero_copy_only=False)
                big = np.abs(x).max(initial=0.0)
                if np.isfinite(x).all() and big > 0:
                    x = x / big  # so that squares neither vanish nor overflow
                    x /= np.sqrt((x * x).sum())
                    x += 0.0  # one zero
                    ids.append(i)
                    parts.append(part)
                    out.append(x.tobytes())
                    half.append(x.astype(np.float16).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(parts, pa.int64()), pa.array(out, pa.binary()), pa.array(half, pa.binary())], names=["vec_id", "part", "v", "u"])

    v = F.col(vector_col)
    ok = rows.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull()))
    ok = ok.select(F.col(id_col).cast("long").alias("vec_id"), F.xxhash64(F.col(label_col), F.size(v)).alias("part"), v.cast("array<double>").alias("x"))
    return ok.mapInArrow(run, "vec_id long, part long, v binary, u binary")


def _sizes(nodes: DataFrame) -> DataFrame:
    """Number of vectors and mean of each label (and length): one small row each, summed in the tasks first."""

    def mean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, list] = {}
        for batch in batches:
            parts = batch.column(0).to_numpy()
            for part in np.unique(parts):
                x = _vectors(batch.column(1).take(pa.array(np.flatnonzero(parts == part))))
                s = sums.setdefault(int(part), [np.zeros(x.shape[1]), 0])
                s[0] = s[0] + x.sum(0)
                s[1] += len(x)
        at = [(p, i, float(s[0][i]), s[1]) for p, s in sums.items() for i in range(len(s[0]))]
        yield pa.RecordBatch.from_arrays([pa.array([a[c] for a in at], t) for c, t in enumerate((pa.int64(), pa.int32(), pa.float64(), pa.int64()))], names=["part", "i", "s", "n"])

    sums = nodes.select("part", "v").mapInArrow(mean, "part long, i int, s double, n long").groupBy("part", "i").agg(F.sum("s").alias("s"), F.sum("n").alias("n"))
    return sums.groupBy("part").agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("i", (F.col("s") / F.col("n")).alias("s")))), lambda x: x["s"]).alias("mean"))


def _leaves(nodes: DataFrame, sizes: DataFrame, trees: int, seed: int) -> DataFrame:
    """Rows (leaf, tree, node): each vector in one leaf of each tree."""
    frames = nodes.join(base.checked_broadcast(sizes), "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            ids, parts, ns = (c.to_numpy(zero_copy_only=False) for c in (batch.column(0), batch.column(1), batch.column(3)))
            leaf = np.zeros((len(ids), trees), np.int64)
            means = batch.column(4)
            for part in np.unique(parts):
                at = np.flatnonzero(parts == part)
                x = _vectors(batch.column(2).take(pa.array(at)), np.float16).astype(np.float32)
                mean = np.array(means[int(at[0])].as_py(), np.float32)
                bits = max(0, int(np.ceil(np.log2(max(1.0, ns[at[0]] / LEAF)))))
                if x.shape[1] not in planes:
                    planes[x.shape[1]] = np.random.default_rng(seed).normal(size=(x.shape[1], trees * 48)).astype(np.float32)
                side = ((x - mean) @ planes[x.shape[1]] > 0).reshape(len(at), trees, 48)[:, :, : min(bits, 48)]
                code = (side * (np.int64(1) << np.arange(side.shape[2]))).sum(2)
                tag = base.mix64(np.full(1, part).astype(np.int64).view(np.uint64) + np.uint64(seed))
                mixed = base.mix64(code.astype(np.uint64) ^ tag)
                leaf[at] = base.mix64(mixed + np.arange(trees, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(leaf.ravel()), pa.array(np.tile(np.arange(trees, dtype=np.int32), len(ids))), pa.array(np.repeat(ids, trees))], names=["leaf", "tree", "node"])

    keyed = frames.select("node", "part", "u", "n", "mean").mapInArrow(run, "leaf long, tree int, node long")
    keyed = base.stored(keyed, "vector_leaves")
    counts = base.stored(keyed.groupBy("leaf").agg(F.count("*").alias("m")).where(F.col("m") > 2 * LEAF), "vector_large_leaves")
    keyed = keyed.join(base.checked_broadcast(counts), "leaf", "left")
    piece = F.when(F.col("m").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("node", F.lit(seed)), F.ceil(F.col("m") / LEAF)))
    return base.stored(keyed.select(F.xxhash64("leaf", piece).alias("leaf"), "tree", "node"), "vector_pieces")


def _all_pairs(k: int, most: int, threshold: float) -> Callable:
    """Best k of each member among the members of a group, as directed edges; up to `most` where that many may be links."""

    def fn(t: pa.Table):
        n = t.num_rows
        if n < 2:
            return None
        ids, x = t.column(1).to_numpy(), _vectors(t.column(2), np.float16).astype(np.float32)
        s = x @ x.T
        s[ids[:, None] == ids[None, :]] = -2
        kk, mm = min(k, n - 1), min(most, n - 1)
        best = np.argpartition(-s, kk - 1, axis=1)[:, :kk]
        a, b, c = [np.repeat(ids, kk)], [ids[best].ravel()], [np.take_along_axis(s, best, 1).ravel()]
        wide = np.flatnonzero((s >= threshold - SLACK).sum(1) > kk)
        if len(wide):
            best = np.argpartition(-s[wide], mm - 1, axis=1)[:, :mm]
            a.append(np.repeat(ids[wide], mm))
            b.append(ids[best].ravel())
            c.append(np.take_along_axis(s[wide], best, 1).ravel())
            c[-1][c[-1] < threshold - SLACK] = -2
        a, b, c = map(np.concatenate, (a, b, c))
        keep = c > -2
        return a[keep], b[keep], c[keep]

    return fn


def _best(edges: DataFrame, k: int, most: int, threshold: float) -> DataFrame:
    """The k best distinct neighbours of each node, and further ones that may be links up to `most`."""
    edges = edges.groupBy("a", "b").agg(F.max("s").alias("s"), F.max("old").alias("old"))
    rank = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))
    ranked = edges.withColumn("r", rank).where(F.col("r") <= most)
    return ranked.where((F.col("r") <= k) | (F.col("s") >= threshold - SLACK)).select("a", "b", "s", "old", "r")


def _meet(t: pa.Table):
    """Centres of a leaf: pairs of their members with a new side that would enter either's list.

    Rows with a vector (kind 0) describe members, the others say which centre has which.
    """
    kind = t.column(1).to_numpy()
    about, held = t.filter(pa.array(kind == 0)), t.filter(pa.array(kind == 1))
    if about.num_rows < 2 or not held.num_rows:
        return None
    ids = about.column(3).to_numpy()
    order = np.argsort(ids)
    ids, least, x = ids[order], about.column(5).to_numpy()[order], _vectors(about.column(6), np.float16)[order].astype(np.float32)
    centre, member, new = (held.column(c).to_numpy() for c in (2, 3, 4))
    order = np.argsort(centre, kind="stable")
    centre, member, new = centre[order], np.searchsorted(ids, member[order]), new[order]
    cuts = [0, *(np.flatnonzero(centre[1:] != centre[:-1]) + 1), len(centre)]
    codes, found = [], []
    for a, b in zip(cuts, cuts[1:]):
        m, first = np.unique(member[a:b], return_index=True)
        fresh = np.zeros(len(m), bool)
        np.logical_or.at(fresh, np.searchsorted(m, member[a:b]), new[a:b] > 0)
        s = x[m] @ x[m].T
        i, j = np.nonzero(np.triu((fresh[:, None] | fresh[None, :]) & (s > np.minimum(least[m][:, None], least[m][None, :])), 1))
        if len(i):
            codes.append(m[i].astype(np.int64) * len(ids) + m[j])
            found.append(s[i, j])
    if not codes:
        return None
    codes, first = np.unique(np.concatenate(codes), return_index=True)
    s = np.concatenate(found)[first].astype(np.float64)
    i, j = codes // len(ids), codes % len(ids)
    at, to = s > least[i], s > least[j]
    return np.concatenate([ids[i[at]], ids[j[to]]]), np.concatenate([ids[j[at]], ids[i[to]]]), np.concatenate([s[at], s[to]])


def descend(nodes: DataFrame, homes: DataFrame, graph: DataFrame, k: int, most: int, rounds: int, threshold: float, settle: float = 0.01) -> DataFrame:
    """Refine directed edges (a, b, s, old, r) by neighbours of neighbours."""
    for _ in range(rounds):
        least = graph.groupBy("a").agg(F.when(F.count("*") >= k, F.min(F.when(F.col("r") <= k, F.col("s")))).otherwise(F.lit(-2.0)).alias("least"))
        lists = graph.where(F.col("r") <= k)
        near = lists.select(F.col("a").alias("c"), F.col("b").alias("m"), (1 - F.col("old")).alias("new"))
        # reverse lists are cut to k by hash; a first cut by salt keeps a popular vector's list out of one task
        turned = lists.select(F.col("b").alias("c"), F.col("a").alias("m"), (1 - F.col("old")).alias("new"), F.pmod(F.xxhash64("a"), F.lit(16)).alias("salt"))
        order = [F.desc("new"), F.xxhash64("m", "c")]
        for by in (("c", "salt"), ("c",)):
            turned = turned.withColumn("x", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("x") <= k).drop("x")
        members = near.union(turned.drop("salt"))
        lively = members.where("new > 0").select("c").distinct()
        members = members.join(lively, "c").join(homes.select(F.col("node").alias("c"), "leaf"), "c").select("leaf", "c", "m", F.col("new").cast("int").alias("new"))
        members = base.stored(members, "vector_members")
        about = members.select("leaf", "m").distinct().join(nodes.select(F.col("node").alias("m"), "u"), "m").join(least.withColumnRenamed("a", "m"), "m", "left")
        about = about.select("leaf", F.lit(0).alias("kind"), F.lit(0).cast("long").alias("c"), "m", F.lit(0).alias("new"), F.coalesce("least", F.lit(-2.0)).alias("least"), "u")
        held = members.select("leaf", F.lit(1).alias("kind"), "c", "m", "new", F.lit(0.0).alias("least"), F.lit(None).cast("binary").alias("u"))
        found = _by_key(about.union(held), "leaf", _meet, "a long, b long, s double")
        merged = graph.select("a", "b", "s", F.lit(1).alias("old")).union(found.withColumn("old", F.lit(0)))
        graph = base.stored(_best(merged, k, most, threshold), "vector_graph")
        may = graph.where(F.col("s") >= threshold - SLACK).agg(F.count("*").alias("n"), F.count_if(F.col("old") == 0).alias("new")).first()
        if may["new"] <= settle * may["n"]:
            break
    return graph


def _blocks(queries: DataFrame, nodes: DataFrame) -> DataFrame:
    """Rows (t, node, side, full, copies, v): every block of queries meets every block of its part's vectors in a task t."""
    def count(df: DataFrame, name: str) -> DataFrame:
        return df.groupBy("part").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias(name))

    per = base.checked_broadcast(base.stored(count(queries, "qb").join(count(nodes, "nb"), "part"), "vector_blocks"))
    q = queries.join(per, "part").withColumn("i", F.pmod(F.xxhash64("node"), F.col("qb")))
    q = q.select("part", "node", "v", "full", "copies", F.lit(0).alias("side"), "i", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)).alias("j"))
    d = nodes.join(per, "part").withColumn("j", F.pmod(F.xxhash64("node"), F.col("nb")))
    d = d.select("part", "node", "v", "full", "copies", F.lit(1).alias("side"), F.explode(F.sequence(F.lit(0), F.col("qb") - 1)).alias("i"), "j")
    both = q.unionByName(d)
    return both.select(F.xxhash64("part", F.col("i").cast("long"), F.col("j").cast("long")).alias("t"), "node", "side", "full", "copies", "v")


def _sides(t: pa.Table) -> tuple | None:
    ids, side = t.column(1).to_numpy(), t.column(2).to_numpy()
    if side.all() or not side.any():
        return None
    return ids, _vectors(t.column(5)), np.flatnonzero(side == 0), np.flatnonzero(side == 1)


def _pairs_within(threshold: float) -> Callable:
    """Links (a = query, b) of a pair of blocks."""

    def fn(t: pa.Table):
        got = _sides(t)
        if got is None:
            return None
        ids, x, a, b = got
        i, j = np.nonzero(within(x[a], x[b], threshold) & (ids[a][:, None] != ids[b][None, :]))
        return ids[a[i]], ids[b[j]]

    return fn


def _counts_within(threshold: float) -> Callable:
    """Of a pair of blocks: (kind 0, node, number of rows linked with it) and (kind 1, node, the least node it is connected to here)."""

    def fn(t: pa.Table):
        got = _sides(t)
        if got is None:
            return None
        ids, x, a, b = got
        full, copies = t.column(3).to_numpy(zero_copy_only=False).astype(bool), t.column(4).to_numpy()
        hit = np.concatenate([within(x[a[k : k + 256]], x[b], threshold) for k in range(0, len(a), 256)])
        hit &= ids[a][:, None] != ids[b][None, :]
        of_a, of_b = hit @ copies[b], copies[a] @ hit
        of_b[full[b]] = 0  # counted where they are the queries
        label_a, label_b = np.argsort(np.argsort(ids))[a].astype(np.int32), np.argsort(np.argsort(ids))[b].astype(np.int32)
        some_a, some_b = hit.any(1), hit.any(0)
        while some_a.any():
            before = label_a.copy(), label_b.copy()
            for k in np.flatnonzero(some_a):
                label_a[k] = min(label_a[k], label_b[hit[k]].min())
            for k in np.flatnonzero(some_b):
                label_b[k] = min(label_b[k], label_a[hit[:, k]].min())
            if (before[0] == label_a).all() and (before[1] == label_b).all():
                break
        rank = np.sort(ids)
        out = [(0, ids[a], of_a, of_a > 0), (0, ids[b], of_b, of_b > 0), (1, ids[a], rank[label_a], some_a), (1, ids[b], rank[label_b], some_b)]
        return tuple(np.concatenate(c) for c in zip(*[(np.full(int(ok.sum()), kind, np.int32), n[ok], m[ok]) for kind, n, m, ok in out]))

    return fn


def _confirmed(pairs: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """Those of the pairs (a < b) that are links."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                sizes = np.diff(np.frombuffer(batch.column(2).buffers()[1], np.int32)[batch.column(2).offset : batch.column(2).offset + batch.num_rows + 1])
                ok = np.zeros(batch.num_rows, bool)
                for n in np.unique(sizes):
                    at = pa.array(np.flatnonzero(sizes == n))
                    ok[sizes == n] = cosines(_vectors(batch.column(2).take(at)), _vectors(batch.column(3).take(at))) >= threshold
                yield pa.RecordBatch.from_arrays(batch.columns[:2], names=["a", "b"]).filter(pa.array(ok))

    v = nodes.select("node", "v")
    rows = pairs.join(v.toDF("a", "v"), "a").join(v.toDF("b", "w"), "b").select("a", "b", "v", "w")
    return rows.mapInArrow(run, "a long, b long")


def _both(pairs: DataFrame) -> DataFrame:
    return pairs.select("a", "b").union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _crowded(pairs: DataFrame, most: int) -> DataFrame:
    """Nodes of at least `most` pairs."""
    return _both(pairs).groupBy(F.col("a").alias("node")).agg(F.count("*").alias("n")).where(F.col("n") >= most).select("node")


def _without(pairs: DataFrame, full: DataFrame) -> DataFrame:
    return pairs.join(full.select(F.col("node").alias("a")), "a", "left_anti").join(full.select(F.col("node").alias("b")), "b", "left_anti").select("a", "b")


def _close(pairs: DataFrame, full: DataFrame, nodes: DataFrame, most: int, threshold: float) -> tuple[DataFrame, DataFrame]:
    """(pairs a < b of vectors that are not full, full vectors), the pairs closed over two hops."""
    fresh = pairs
    while not fresh.isEmpty():
        own = _both(fresh).select("a", F.col("b").alias("m"))
        steps = own.join(_both(pairs).select(F.col("a").alias("m"), "b"), "m")
        steps = steps.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct()
        fresh = base.stored(_confirmed(steps.join(pairs, ["a", "b"], "left_anti"), nodes, threshold), "vector_fresh")
        pairs = base.stored(pairs.union(fresh), "vector_links")
        more = base.stored(_crowded(pairs, most), "vector_full")
        if not more.isEmpty():
            full = base.stored(full.union(more), "vector_full")
            pairs, fresh = base.stored(_without(pairs, more), "vector_links"), base.stored(_without(fresh, more), "vector_fresh")
    return pairs, full


def link_graph(nodes: DataFrame, k: int = 16, most: int = 64, trees: int = 4, rounds: int = 5, threshold: float = THRESHOLD, audit: int = 256, seen: int = 200, recall: float = 0.98, attempts: int = 3, seed: int = 5) -> tuple[DataFrame, DataFrame, float | None]:
    """(pairs a < b of vectors that are not full, the full vectors, measured recall) of distinct vectors (node, part, v, u, copies).

    All links of a full vector are found by `counted`.  The recall is that of the pairs
    (1 for the full); null if no link was met in the audit.
    """
    sizes = base.stored(_sizes(nodes), "vector_parts")
    total = nodes.count()
    unit = F.pmod(F.xxhash64("node", F.lit(seed)), F.lit(1_000_000))
    plain = nodes.select("node", "part", "v", "copies", F.lit(False).alias("full"))
    for wider in (1, 4, 16):
        sample = plain.where(unit < 1_000_000 * min(1.0, wider * audit / max(1, total)))
        truth = base.stored(_by_key(_blocks(sample, plain), "t", _pairs_within(threshold), "a long, b long"), "vector_audit")
        wanted = truth.count()
        if wanted >= seen or wider * audit >= total:
            break
    pairs = full = got = None
    for attempt in range(attempts):
        leaves = _leaves(nodes, sizes, trees, seed + 100 * attempt)
        start = leaves.join(nodes.select("node", "u"), "node").select("leaf", "node", "u")
        start = _by_key(start, "leaf", _all_pairs(k, most, threshold), "a long, b long, s double").withColumn("old", F.lit(0))
        graph = base.stored(_best(start, k, most, threshold), "vector_graph")
        graph = descend(nodes, leaves.where("tree = 0"), graph, k, most, rounds, threshold)
        may = graph.where(F.col("s") >= threshold - SLACK).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        found = base.stored(_confirmed(may, nodes, threshold), "vector_links")
        if pairs is not None:
            found = base.stored(_without(pairs.union(found).distinct(), full), "vector_links")
        crowd = _crowded(found, most)
        full = base.stored(crowd if full is None else full.union(crowd), "vector_full")
        pairs, full = _close(base.stored(_without(found, full), "vector_links"), full, nodes, most, threshold)
        left = truth.join(full.select(F.col("node").alias("a")), "a", "left_anti").join(full.select(F.col("node").alias("b")), "b", "left_anti")
        missed = left.select("a", "b").join(_both(pairs), ["a", "b"], "left_anti").count()
        got = 1 - missed / wanted if wanted else None
        if got is None or got >= recall:
            return pairs, full, got
    return pairs.limit(0), base.stored(nodes.select("node"), "vector_full"), 1.0


def counted(full: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """Rows (kind, a, b) of `_counts_within` of the full vectors against all."""
    marked = nodes.join(full.select("node", F.lit(True).alias("full")), "node", "left")
    marked = base.stored(marked.select("node", "part", "v", "copies", F.coalesce("full", F.lit(False)).alias("full")), "vector_marked")
    return base.stored(_by_key(_blocks(marked.where("full"), marked), "t", _counts_within(threshold), "kind int, a long, b long"), "vector_counts")


def _nodes(unit: DataFrame) -> DataFrame:
    """Distinct vectors (node, part, v, u, copies, least). A node is a hash of part and vector, salted until no two share one."""
    for salt in range(8):
        hashed = unit.groupBy("part", "v").agg(F.first("u").alias("u"), F.count("*").alias("copies"), F.min("vec_id").alias("least"))
        nodes = base.stored(hashed.withColumn("node", F.xxhash64(F.lit(salt), "part", "v")), "vector_nodes")
        if nodes.groupBy("node").count().where("count > 1").isEmpty():
            return nodes
    raise RuntimeError("vectors keep sharing hashes")


def near_duplicate_vectors(rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD, **options) -> DataFrame:
    """Rows (vec_id, n_links, component_id, kept, recall), one per row. options: those of link_graph."""
    unit = base.stored(normalised(rows, id_col, vector_col, label_col), "vector_unit")
    nodes = _nodes(unit)
    pairs, full, recall = link_graph(nodes.select("node", "part", "v", "u", "copies"), threshold=threshold, **options)
    small = nodes.select("node", "copies", "least")
    others = _both(pairs).join(small.select(F.col("node").alias("b"), "copies"), "b").select(F.col("a").alias("node"), F.col("copies").alias("n"))
    ends = pairs.select("a", "b")
    if not full.isEmpty():
        counts = counted(full, nodes, threshold)
        others = others.union(counts.where("kind = 0").select("a", "b"))
        ends = ends.union(counts.where("kind = 1 and a <> b").select("a", "b"))
    found = base.components(ends, "vector_components")
    degree = others.groupBy("node").agg(F.sum("n").alias("others"))
    # a group of connected vectors has the least id of its rows; rows that share an id connect their groups
    placed = small.join(found, "node", "left").join(degree, "node", "left")
    placed = base.stored(placed.select("node", "copies", "least", F.coalesce("component", "node").alias("group"), F.coalesce("others", F.lit(0)).alias("others")), "vector_placed")
    least = placed.groupBy("group").agg(F.min("least").alias("first"))
    placed = placed.join(least, "group").select("node", "copies", "others", "first")
    per_row = unit.select("part", "v", "vec_id").join(nodes.select("part", "v", "node"), ["part", "v"]).join(placed, "node")
    valid = base.stored(per_row.select("vec_id", (F.col("others") + F.col("copies") - 1).alias("n_links"), "first"), "vector_rows")
    named = valid.groupBy("vec_id").agg(F.min("first").alias("component"), F.max("first").alias("other"))
    if not named.where("component <> other").isEmpty():
        named = base.components(valid.select(F.col("vec_id").alias("a"), F.col("first").alias("b")), "vector_ids").withColumnRenamed("node", "vec_id")
    rest = rows.select(F.col(id_col).cast("long").alias("vec_id")).groupBy("vec_id").agg(F.count("*").alias("all"))
    rest = rest.join(valid.groupBy("vec_id").agg(F.count("*").alias("ok")), "vec_id", "left")
    rest = rest.select("vec_id", F.explode(F.expr("array_repeat(0L, cast(all - coalesce(ok, 0) as int))")).alias("n_links"))
    out = valid.select("vec_id", "n_links").union(rest).join(named.select("vec_id", "component"), "vec_id", "left")
    out = out.select("vec_id", F.col("n_links").cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id")).withColumn("recall", F.lit(recall).cast("double"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(base.table(spark, sf_dir, "embeddings"))
