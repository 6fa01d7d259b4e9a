"""What the operators of this subpackage share: tables, scratch space, hashing, caches."""

from __future__ import annotations

import ctypes
import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from runstore.catalog import scratch_folder

#: Bytes a broadcast may hold once counted; beyond it joins shuffle.
BROADCAST_BYTES = 64 << 20
#: Rows of one key that a join leaves to one task; keys with more are broadcast, and few by their number.
HUB, HUBS = 64, 50_000


def bounded_batches(spark: SparkSession, rows: int = 1000) -> None:
    """At most so many rows in an Arrow batch from here on: texts may be long, and batches are held whole."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key, "10000")) > rows:
        spark.conf.set(key, str(rows))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder below the shared checkpoint folder; it goes when the program ends."""
    return scratch_folder(spark, name)


def stored(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write df to scratch space and read it back: lineage ends, lost executors cost nothing."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def checked_broadcast(df: DataFrame, rows: int | None = None, limit: int | None = None) -> DataFrame:
    """df with a broadcast hint if its bytes, counted first, are within the limit, else df as it is.

    rows: a count known already, for frames whose columns are all of fixed width.
    """
    weight: Column = F.lit(16)
    for f in df.schema.fields:
        c = F.col(f"`{f.name}`")
        match f.dataType:
            case T.StringType() | T.BinaryType():
                weight = weight + F.coalesce(F.octet_length(c), F.lit(0)) + 16
            case T.ArrayType() | T.MapType():
                weight = weight + F.coalesce(F.size(c), F.lit(0)) * 48 + 16
            case _:
                weight = weight + 8
    if rows is None or any(isinstance(f.dataType, (T.StringType, T.BinaryType, T.ArrayType, T.MapType)) for f in df.schema.fields):
        size = df.agg(F.sum(weight)).first()[0] or 0
    else:
        size = rows * (16 + 8 * len(df.columns))
    return F.broadcast(df) if size <= (BROADCAST_BYTES if limit is None else limit) else df


def join_by_hubs(rows: DataFrame, table: DataFrame, key: str, count: str, total: int) -> DataFrame:
    """Inner join of rows with a stored table of one row a key, whose column `count` says how many rows have that key.

    Keys of many rows go by broadcast: their number is bounded by `HUBS` (or by the
    rows, over `HUB`) whatever the data, so no key's rows meet in one task.
    """
    most = max(HUB, total // HUBS)
    hot = F.broadcast(table.where(F.col(count) > most).drop(count))
    seldom = table.where(F.col(count) <= most).drop(count)
    found = rows.join(hot, key)
    rest = rows.join(hot.select(key), key, "left_anti")
    return found.unionByName(rest.join(seldom, key))


def slices(texts: pa.Array, most: int) -> Iterator[tuple[int, int]]:
    """(from, to) of stretches of a text column of at most so many bytes; a longer text stands alone."""
    sizes = pc.binary_length(texts).fill_null(0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes, dtype=np.int64)
    at = 0
    while at < len(sizes):
        before = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + most, side="right")))
        yield at, to
        at = to


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: xor-shifts and odd multipliers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_held: dict = {}


def held(key: tuple, make: Callable):
    """What make gives, kept in this Python worker until another operator asks for its own.

    Workers outlive tasks and stages, so only one operator's state stays.
    """
    if key not in _held:
        if _held:
            _held.clear()
            try:
                ctypes.CDLL(None).malloc_trim(0)  # hand freed memory back, where the C library can
            except (AttributeError, OSError):
                pass
        _held[key] = make()
    return _held[key]


class TwoGenerationCache:
    """A bounded dict: when the young generation is full it becomes the old one.

    Entries met again move back into the young one, so frequent words stay.
    """

    def __init__(self, limit: int):
        self.limit, self.young, self.old = limit, {}, {}

    def ensure(self, keys: Iterable, make: Callable[[list], Iterable]) -> dict:
        """A dict that has every key; make gets the list of those not known yet."""
        young = self.young
        missing = [k for k in dict.fromkeys(keys) if k not in young]
        if missing:
            if len(young) + len(missing) > self.limit and young:
                self.old, self.young = young, {}
                young = self.young
                missing = list(dict.fromkeys(keys))
            old = self.old
            fresh = []
            for k in missing:
                v = old.get(k)
                if v is None:
                    fresh.append(k)
                else:
                    young[k] = v
            if fresh:
                young.update(zip(fresh, make(fresh)))
        return young


def components(edges: DataFrame, name: str = "components", max_rounds: int = 60) -> DataFrame:
    """Connected components of the undirected edges (a, b): rows (node, component = least node).

    Alternates two contractions (every node's larger neighbours, then its
    smaller ones, are hung on its least neighbour) until nothing moves; each
    round is written to scratch space.  The rounds grow with the logarithm of
    a component's size.  A hub's neighbours are never gathered: minima are
    aggregated in the tasks first, and those of hubs are joined back by broadcast.
    """
    current = stored(
        edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), name
    )
    for _ in range(max_rounds):
        n, nodes = current.agg(F.count("*"), F.count_distinct("a")).first()
        # done: every node hangs on one other, which hangs on none
        if n == nodes and current.select("b").join(current.select(F.col("a").alias("b")), "b", "left_semi").isEmpty():
            break
        both = current.union(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = stored(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("n")), name)
        large = join_by_hubs(both, least, "a", "n", 2 * n)
        large = stored(large.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct(), name)
        down = stored(large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")), name)
        moved = join_by_hubs(large, down, "a", "n", 2 * n)
        small = moved.select(F.col("b").alias("a"), F.col("m").alias("b")).union(down.select("a", F.col("m").alias("b")))
        current = stored(small.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), name)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = current.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return current.select(F.col("a").alias("node"), F.col("b").alias("component")).union(roots)


def digits(n: int) -> int:
    return max(1, math.ceil(math.log2(max(2, n))))
