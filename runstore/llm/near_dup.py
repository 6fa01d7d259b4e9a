"""Operator 4: near-duplicate documents by min-max hashing.

A document's set holds its distinct shingles (five words in a row, lower-cased
in ASCII; a shorter text is one shingle), as 64-bit hashes: within the two sets
of one comparison a clash is out of the question at any corpus size.  Each
random permutation of the hashes gives two signature values, the least and the
greatest member under it, so half the hash evaluations of plain MinHash make a
signature whose agreement estimates the Jaccard similarity without bias and
with lower variance.  Signatures are cut into bands; documents that share a
band are candidates (at similarity 0.85 the 24 bands of 6 values miss a pair
with probability about 1e-5; `bands_for` gives the number for other
thresholds), and links are confirmed on full sets.  `recall_of` measures what
the bands miss: the documents whose id is divisible by 100 against all.

Equal sets are collapsed first, by a fingerprint of 128 bits and their size.
Candidates are not listed as pairs.  In each band one member (the least; in
later rounds one of the smallest group) is compared with all members that are
not connected with it yet, and is then done.  Links found connect members, and a
band is closed when its members are connected or done: a group of m near copies
costs m comparisons, in tasks of bounded size.  What is still open after
`ROUNDS` rounds (bands of many members that are alike and yet not linked) is
compared in full: open bands are joined into clusters, a cluster is cut into
blocks by size class (linked sets differ in size by the threshold at most, so
only equal or adjacent classes meet) and hash, and each pair of blocks is a task
of its own.  Work in such a cluster is quadratic in the worst case; nothing is
capped.

A null or empty text, or one without words, has an empty set and links with
nothing.  A very long text is one set like any other: tasks hold two blocks of
sets at most and single sets of what is compared with one member.  Rows with
one id count as one document.  Rows with a null id are not linked: their
component and kept are null.  An empty table gives no rows.  Other columns,
whatever their names, are not read by `near_duplicates`; `deduplicate` keeps
them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

SHINGLE, BANDS, BAND_ROWS, PERCENT = 5, 24, 6, 85
#: Members of a block; a cluster of at most this many is one task.
BLOCK = 128
#: Members that one task compares with a band's chosen one, and rounds of that.
STAR, ROUNDS = 512, 3
_CHUNK = 1 << 15
_STEP = np.uint64(0x9E3779B97F4A7C15)


def shingles(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """The sorted distinct shingle hashes of a whole text."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    n = min(size, len(words))
    out = np.full(len(words) - n + 1, n, np.uint64)
    for k in range(n):
        out = base.mix64(out * _STEP + h[k : len(h) - n + 1 + k])
    return np.unique(out)


class MinMaxHasher:
    """Banded min-max signatures."""

    def __init__(self, bands: int = BANDS, rows: int = BAND_ROWS, seed: int = 1):
        if bands * rows % 2:
            raise ValueError("signature values come in pairs")
        rng = np.random.default_rng(seed)
        self.bands, self.rows = bands, rows
        self.factors = rng.integers(0, 1 << 63, bands * rows // 2, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def signature(self, s: np.ndarray) -> np.ndarray:
        """Least and greatest member of a set under every permutation."""
        low = high = None
        for a in range(0, len(s), _CHUNK):
            y = self.factors[:, None] * s[None, a : a + _CHUNK]
            y ^= y >> np.uint64(32)
            lo, hi = y.min(1), y.max(1)
            low, high = (lo, hi) if low is None else (np.minimum(low, lo), np.maximum(high, hi))
        return np.stack([low, high], 1).ravel()

    def band_keys(self, s: np.ndarray) -> np.ndarray:
        v = self.signature(s).reshape(self.bands, self.rows)
        key = np.arange(self.bands, dtype=np.uint64)
        for k in range(self.rows):
            key = base.mix64(key * _STEP + v[:, k])
        return key.view(np.int64)


def linked(a: int, b: int, both: int, percent: int) -> bool:
    return 100 * both >= percent * (a + b - both)


def forest(sets: list[np.ndarray], sides: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Spanning forest of the links among sets (sides all 0) or between the two sides."""
    m = len(sets)
    parent = list(range(m))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    out = []

    def join(i: int, j: int) -> None:
        a, b = root(i), root(j)
        if a != b:
            parent[a] = b
            out.append((i, j))

    if m == 2:
        both = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        if linked(len(sets[0]), len(sets[1]), both, percent):
            join(0, 1)
        return out
    sizes = np.array([len(s) for s in sets])
    values = np.concatenate(sets)
    owner = np.repeat(np.arange(m), sizes)
    order = np.argsort(values, kind="stable")
    owner_sorted = owner[order]
    fresh = np.concatenate([[True], values[order][1:] != values[order][:-1]])
    group = np.empty(len(values), np.int64)
    group[order] = np.cumsum(fresh) - 1
    starts = np.flatnonzero(fresh)
    lengths = np.diff(np.append(starts, len(values)))
    ends = np.cumsum(sizes)
    two = bool(sides.any())
    for i in range(m):
        if two and sides[i]:
            continue
        g = group[ends[i] - sizes[i] : ends[i]]
        g = g[lengths[g] > 1]
        if not len(g):
            continue
        n = lengths[g]
        at = np.repeat(starts[g] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        both = np.bincount(owner_sorted[at], minlength=m)
        hit = 100 * both >= percent * (sizes + sizes[i] - both)
        hit[i] = False
        if two:
            hit &= sides == 1
        for j in np.flatnonzero(hit):
            join(i, int(j))
    return out


def sketch(docs: DataFrame, id_col: str, text_col: str, hasher: MinMaxHasher) -> DataFrame:
    """Rows (doc_id, n_shingles, f1, f2, bands): set size, set fingerprint, band keys (null for empty sets)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, f1, f2, bands = [], [], [], []
            for text in batch.column(1):
                s = shingles(text.as_py())
                sizes.append(len(s))
                f1.append(s.sum(dtype=np.uint64))
                f2.append(base.mix64(s ^ _STEP).sum(dtype=np.uint64))
                bands.append(hasher.band_keys(s) if len(s) else None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(sizes, pa.int64()), pa.array(np.array(f1, np.uint64).view(np.int64)), pa.array(np.array(f2, np.uint64).view(np.int64)), pa.array(bands, pa.list_(pa.int64()))],
                names=["doc_id", "n_shingles", "f1", "f2", "bands"],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t"))
    return rows.mapInArrow(run, "doc_id long, n_shingles long, f1 long, f2 long, bands array<long>")


def bands_for(percent: int, rows: int = BAND_ROWS, miss: float = 1e-5) -> int:
    """Bands that miss a pair at the threshold with at most this probability (an even number)."""
    return 2 * math.ceil(math.log(miss) / math.log1p(-((percent / 100) ** rows)) / 2)


def _set_rows(docs: DataFrame, tasks: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows (task, side, node, s): the sets that tasks (node, task, side) ask for, each task's together, side 0 first."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, own = None, b""
        for batch in batches:
            out = []
            for node, text in zip(batch.column(0).to_pylist(), batch.column(3)):
                if node != last:  # a node's tasks follow each other
                    last, own = node, shingles(text.as_py()).tobytes()
                out.append(own)
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), batch.column(0), pa.array(out, pa.binary())], names=["task", "side", "node", "s"])

    keyed = docs.select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("t"))
    keyed = keyed.join(base.checked_broadcast(tasks), "node").select("node", "task", "side", "t")
    keyed = keyed.mapInArrow(sets, "task long, side int, node long, s binary")
    return keyed.repartition("task").sortWithinPartitions("task", "side", "node")


def _by_star(docs: DataFrame, pairs: DataFrame, id_col: str, text_col: str, percent: int) -> DataFrame:
    """Those of the pairs (a: a chosen member, b: another) that are links."""
    stars = base.stored(pairs.groupBy("a").agg(F.ceil(F.count("*") / STAR).cast("int").alias("parts"), F.count("*").alias("n")), "near_dup_stars")
    total = stars.agg(F.sum("n")).first()[0] or 0
    part = F.pmod(F.xxhash64("b"), F.col("parts")).cast("int")
    members = base.join_by_hubs(pairs, stars, "a", "n", total).select(F.col("b").alias("node"), F.xxhash64("a", part).alias("task"), F.lit(1).alias("side"))
    centres = stars.select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).select(F.col("a").alias("node"), F.xxhash64("a", "part").alias("task"), F.lit(0).alias("side"))
    rows = _set_rows(docs, base.stored(members.union(centres), "near_dup_tasks"), id_col, text_col)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = centre = own = None
        for batch in batches:
            a, b = [], []
            for t, side, node, s in zip(*(c.to_pylist() for c in batch.columns[:3]), batch.column(3)):
                values = np.frombuffer(s.as_buffer(), np.uint64)
                if side == 0:
                    task, centre, own = t, node, np.array(values)
                elif t == task and node != centre and _near(own, values, percent):
                    a.append(centre)
                    b.append(node)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return rows.mapInArrow(compare, "a long, b long")


def _near(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sorted sets are linked."""
    if not linked(len(x), len(y), min(len(x), len(y)), percent):
        return False
    at = np.searchsorted(x, y)
    at[at == len(x)] = 0
    return linked(len(x), len(y), int((x[at] == y).sum()), percent)


def _links(docs: DataFrame, clusters: DataFrame, id_col: str, text_col: str, percent: int) -> DataFrame:
    """Links (a, b) among all members of each cluster, confirmed on full sets, a spanning forest of each task's."""
    size = F.floor(F.log(F.col("n_shingles").cast("double")) / F.lit(-math.log(percent / 100))).cast("int")
    members = clusters.withColumn("class", size)
    per = base.stored(members.groupBy("cluster", "class").agg(F.count("*").alias("n")), "near_dup_sizes")
    total = per.groupBy("cluster").agg(F.sum("n").alias("m"))
    # blocks of each class of each large cluster, and of the classes beside it
    large = per.join(total, "cluster").where(F.col("m") > BLOCK).withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int"))
    beside = large.groupBy("cluster").agg(F.map_from_entries(F.collect_list(F.struct("class", "blocks"))).alias("plan"))
    members = members.join(base.checked_broadcast(base.stored(beside, "near_dup_plans")), "cluster", "left")
    own = F.pmod(F.xxhash64("node"), F.coalesce(F.col("plan")[F.col("class")], F.lit(1))).cast("int")
    members = members.withColumn("block", own)
    same = F.transform(
        F.sequence(F.lit(0), F.col("plan")[F.col("class")] - 1),
        lambda j: F.struct(F.col("class").alias("c1"), F.least(j, F.col("block")).alias("b1"), F.col("class").alias("c2"), F.greatest(j, F.col("block")).alias("b2"), (j < F.col("block")).cast("int").alias("side")),
    )
    up = F.transform(
        F.sequence(F.lit(0), F.col("plan")[F.col("class") + 1] - 1),
        lambda j: F.struct(F.col("class").alias("c1"), F.col("block").alias("b1"), (F.col("class") + 1).alias("c2"), j.alias("b2"), F.lit(0).alias("side")),
    )
    down = F.transform(
        F.sequence(F.lit(0), F.col("plan")[F.col("class") - 1] - 1),
        lambda j: F.struct((F.col("class") - 1).alias("c1"), j.alias("b1"), F.col("class").alias("c2"), F.col("block").alias("b2"), F.lit(1).alias("side")),
    )
    whole = F.array(F.struct(F.lit(0).alias("c1"), F.lit(0).alias("b1"), F.lit(0).alias("c2"), F.lit(0).alias("b2"), F.lit(0).alias("side")))
    none = F.slice(whole, 1, 0)
    tasks = F.when(F.col("plan").isNull(), whole).otherwise(F.concat(same, F.coalesce(up, none), F.coalesce(down, none)))
    tasks = members.select("node", "cluster", F.explode(tasks).alias("k"))
    tasks = tasks.select("node", F.xxhash64("cluster", "k.c1", "k.b1", "k.c2", "k.b2").alias("task"), F.col("k.side").cast("int").alias("side"))
    keyed = _set_rows(docs, base.stored(tasks, "near_dup_tasks"), id_col, text_col)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done() -> pa.RecordBatch:
            got = forest(held, np.array(sides), percent)
            return pa.RecordBatch.from_arrays([pa.array([nodes[i] for i, _ in got], pa.int64()), pa.array([nodes[j] for _, j in got], pa.int64())], names=["a", "b"])

        task, nodes, sides, held = None, [], [], []
        for batch in batches:
            for t, side, node, s in zip(*(c.to_pylist() for c in batch.columns[:3]), batch.column(3)):
                if t != task:
                    if len(nodes) > 1:
                        yield done()
                    task, nodes, sides, held = t, [], [], []
                nodes.append(node)
                sides.append(side)
                held.append(np.frombuffer(s.as_py(), np.uint64))
        if len(nodes) > 1:
            yield done()

    return keyed.mapInArrow(compare, "a long, b long")


def _shared(reps: DataFrame) -> DataFrame:
    """Rows (band, node) of the bands that several sets have."""
    spread = reps.select("node", F.explode("bands").alias("band"))
    counts = spread.groupBy("band").agg(F.count("*").alias("n")).where("n > 1")
    counts = base.stored(counts, "near_dup_bands")
    return base.stored(base.join_by_hubs(spread, counts, "band", "n", counts.agg(F.sum("n")).first()[0] or 0), "near_dup_active")


def _open(active: DataFrame, found: DataFrame | None) -> DataFrame:
    """Rows (band, node, group) of bands whose members are not all connected yet."""
    if found is None:
        return active.withColumn("group", F.col("node"))
    rows = active.join(base.checked_broadcast(found), "node", "left").select("band", "node", F.coalesce("component", "node").alias("group"))
    rows = base.stored(rows, "near_dup_rows")
    several = rows.groupBy("band").agg(F.min("group").alias("x"), F.max("group").alias("y"), F.count("*").alias("n")).where("x < y")
    several = base.stored(several.select("band", "n"), "near_dup_open")
    return base.stored(base.join_by_hubs(rows, several, "band", "n", several.agg(F.sum("n")).first()[0] or 0), "near_dup_rows")


def _connect(docs: DataFrame, reps: DataFrame, id_col: str, text_col: str, percent: int) -> DataFrame:
    """Rows (node, component) of the sets linked with others."""
    active, links, found = _shared(reps), None, None
    for _ in range(ROUNDS):
        rows = _open(active, found)
        groups = rows.groupBy("band", "group").agg(F.count("*").alias("n"), F.min("node").alias("a"))
        chosen = groups.groupBy("band").agg(F.min_by(F.struct("a", "group"), F.struct("n", "a")).alias("x"), F.sum("n").alias("n"))
        chosen = base.stored(chosen.select("band", F.col("x.a").alias("a"), F.col("x.group").alias("own"), "n"), "near_dup_chosen")
        total = chosen.agg(F.sum("n")).first()[0]
        if not total:
            return found if found is not None else _none(docs)
        met = base.stored(base.join_by_hubs(rows, chosen, "band", "n", total), "near_dup_met")
        pairs = met.where("group <> own").select(F.least("a", "node").alias("x"), F.greatest("a", "node").alias("y"), "a", F.col("node").alias("b"))
        pairs = base.stored(pairs.groupBy("x", "y").agg(F.min_by("b", "a").alias("b"), F.min("a").alias("a")).select("a", "b"), "near_dup_pairs")
        more = base.stored(_by_star(docs, pairs, id_col, text_col, percent), "near_dup_links")
        links = more if links is None else links.union(more)
        found = base.stored(base.components(links, "near_dup_components"), "near_dup_found")
        active = base.stored(met.where("node <> a").select("band", "node"), "near_dup_active")
    rows = _open(active, found)
    ends = rows.groupBy("band").agg(F.min("node").alias("a"), F.count("*").alias("n"))
    ends = base.stored(ends, "near_dup_ends")
    total = ends.agg(F.sum("n")).first()[0]
    if not total:
        return found if found is not None else _none(docs)
    edges = base.join_by_hubs(rows.select("band", "node"), ends, "band", "n", total).where("node <> a").select("a", F.col("node").alias("b"))
    clusters = base.components(edges, "near_dup_clusters").withColumnRenamed("component", "cluster")
    clusters = base.stored(clusters.join(reps.select("node", "n_shingles"), "node"), "near_dup_members")
    rest = base.stored(_links(docs, clusters, id_col, text_col, percent), "near_dup_links")
    known = rest if found is None else found.select(F.col("node").alias("a"), F.col("component").alias("b")).union(rest)
    return base.components(known, "near_dup_components")


def _none(docs: DataFrame) -> DataFrame:
    return docs.sparkSession.createDataFrame([], "node long, component long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, bands: int = BANDS, rows: int = BAND_ROWS) -> DataFrame:
    """Rows (doc_id, n_shingles, component_id, kept), one per row of docs."""
    sketches = base.stored(sketch(docs, id_col, text_col, MinMaxHasher(bands, rows)), "near_dup_sketch")
    known = sketches.where("doc_id is not null and n_shingles > 0")
    reps = known.groupBy("f1", "f2", "n_shingles").agg(F.min("doc_id").alias("node"), F.count("*").alias("copies"), F.first("bands").alias("bands"))
    reps = base.stored(reps, "near_dup_reps")
    found = _connect(docs, reps, id_col, text_col, percent)
    placed = reps.join(found, "node", "left").select("f1", "f2", "n_shingles", "copies", "node", F.coalesce("component", "node").alias("component"))
    placed = base.stored(placed.where("copies > 1 or component <> node").select("f1", "f2", "n_shingles", "component"), "near_dup_placed")
    out = sketches.select("doc_id", "n_shingles", "f1", "f2").join(placed, ["f1", "f2", "n_shingles"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    out = out.select("doc_id", "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.col("doc_id") == F.col("component_id"))


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT) -> DataFrame:
    """docs without those that a smaller id stands for; of rows with one id all stay. Rows with null ids stay."""
    gone = near_duplicates(docs, id_col, text_col, percent, max(BANDS, bands_for(percent))).where("not kept").select(F.col("doc_id").alias("__gone"))
    gone = base.stored(gone.distinct(), "near_dup_gone")
    return docs.join(base.checked_broadcast(gone), F.col(f"`{id_col}`").cast("long") == F.col("__gone"), "left_anti")


def recall_of(docs: DataFrame, found: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, every: int = 100) -> tuple[int, int]:
    """(links of the documents whose id is divisible by `every` with any other, those of them that `found` has in one component).

    Exact: all documents that share a shingle with such a document are counted
    shingle by shingle, without bands.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for node, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                s = shingles(text.as_py()).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), node)), pa.array(s), pa.array(np.full(len(s), len(s)))], names=["node", "s", "n"])

    rows = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("t"))
    sets = rows.mapInArrow(spread, "node long, s long, n long")
    asked = base.stored(sets.where(F.col("node") % every == 0), "near_dup_asked")
    both = asked.toDF("a", "s", "na").join(sets.toDF("b", "s", "nb"), "s").where("a <> b").groupBy("a", "b", "na", "nb").agg(F.count("*").alias("x"))
    true = both.where(100 * F.col("x") >= percent * (F.col("na") + F.col("nb") - F.col("x"))).select("a", "b")
    place = found.select("doc_id", "component_id").distinct()
    got = true.join(place.toDF("a", "ca"), "a").join(place.toDF("b", "cb"), "b").agg(F.count("*").alias("n"), F.count_if(F.col("ca") == F.col("cb")).alias("hit")).first()
    return got["n"], got["hit"]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(base.table(spark, sf_dir, "documents"))
