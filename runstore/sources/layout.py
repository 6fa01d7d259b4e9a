"""How run tables lie on disk: by start, by value, with or without counts, delta-coded or in blocks."""

from __future__ import annotations

import math
import uuid
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runstore.spec import Pred, RunTable, Span

#: Bytes of a value of each type in the size model (strings: as counted, 8 by default).
WIDTH = {"int": 4, "bigint": 8, "double": 8, "timestamp_ntz": 4, "date": 4, "string": 8, "boolean": 1}
#: Runs of one file at most, and positions of a run that are handled together.
FILE_RUNS, PIECE = 2_000_000, 1 << 16


def width(kind: str) -> int:
    return WIDTH.get(kind, 8)


def choose(rows: int, runs: int, kind: str, overhead: int = 9) -> str:
    """`points` (f, v for every row) if that is smaller than `runs` (f, v, c)."""
    return "points" if rows * (8 + width(kind) + overhead) < runs * (8 + width(kind) + 8 + overhead) else "runs"


def pieces(df: DataFrame, size: int = PIECE) -> DataFrame:
    """Runs (f, c, others) cut into runs of at most `size` positions, so that what is made of one never is an array of any length."""
    k = df.withColumn("_k", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(c - 1) div {size}"))))
    return k.withColumns({"f": F.col("f") + F.col("_k") * size, "c": F.least(F.col("c") - F.col("_k") * size, F.lit(size).cast("long"))}).drop("_k")


def copies(df: DataFrame, cols: tuple[str, ...]) -> DataFrame:
    """Rows of runs, as often as these are long."""
    return pieces(df.select("f", "c", *[F.col(c).alias(f"_{c}") for c in cols])).select(*[F.col(f"_{c}").alias(c) for c in cols], F.explode(F.sequence(F.lit(1).cast("long"), "c")).alias("_n")).drop("_n")


def positions_of_runs(df: DataFrame) -> DataFrame:
    """Runs (f, c, others), each position a row `pos` with the others."""
    others = [c for c in df.columns if c not in ("f", "c")]
    return pieces(df).select(F.explode(F.sequence("f", F.col("f") + F.col("c") - 1)).alias("pos"), *others)


def delta_options(writer):
    """Second-version Parquet pages code ascending starts as differences; no dictionary for them."""
    return writer.option("parquet.writer.version", "PARQUET_2_0").option("parquet.enable.dictionary#f", "false").option("parquet.enable.dictionary#c", "false")


def write(catalog, rt: DataFrame, projection: str, column: str, depth: int, kind: str, rows: int, runs: int, delta: bool = False) -> RunTable:
    """Two copies of a run table: ordered by start, and by value (covering); each range-split and sorted.

    delta: the copy ordered by start has its starts delta-coded.
    """
    path, by_value = catalog.path(f"{projection}-{column}"), catalog.path(f"{projection}-{column}-by-value")
    if kind == "points":
        rt = positions_of_runs(rt).withColumnRenamed("pos", "f")
    files = max(1, math.ceil((rows if kind == "points" else runs) / FILE_RUNS))
    out = _sorted(rt, files, "f").write
    (delta_options(out) if delta else out).parquet(path)
    stored = catalog.spark.read.schema(rt.schema).parquet(path)
    _sorted(stored, files, "v", "f").write.parquet(by_value)
    return RunTable(projection, column, depth, kind, path, by_value, rows, runs, with_counts(stored))


def _sorted(df: DataFrame, files: int, *cols: str) -> DataFrame:
    split = df.coalesce(1) if files == 1 else df.repartitionByRange(files, *cols)
    return split.sortWithinPartitions(*cols)


def with_counts(df: DataFrame) -> DataFrame:
    return df if "c" in df.columns else df.withColumn("c", F.lit(1).cast("long"))


def inside(spans: Span | list[Span]) -> Column:
    """Whether f lies in a span, or in one of several."""
    spans = [spans] if isinstance(spans, Span) else spans
    return reduce(lambda a, b: a | b, [F.col("f").between(F.lit(s.lo), F.lit(s.hi)) for s in spans])


def read_runs(rt: RunTable, span: Span | list[Span] | None = None) -> DataFrame:
    """A run table, or its runs that start within a span (or several): literals reach the Parquet scan."""
    return rt.frame if span is None else rt.frame.where(inside(span))


def read_by_value(catalog, rt: RunTable, preds: tuple[Pred, ...] = ()) -> DataFrame:
    """Runs whose value passes, from the copy ordered by value."""
    df = catalog.made(("by value", rt.by_value), lambda: catalog.spark.read.schema(rt.frame.schema if rt.layout == "runs" else rt.frame.drop("c").schema).parquet(rt.by_value))
    for p in preds:
        df = df.where(p.on(F.col("v")))
    return with_counts(df)


def write_bucketed(catalog, df: DataFrame, name: str, column: str, buckets: int) -> DataFrame:
    """A table bucketed by a column and sorted by it, at a place in scratch space: equal buckets of two such tables join without a shuffle."""
    table, path = f"{name}_{uuid.uuid4().hex[:12]}", catalog.path(name)
    df.repartition(buckets, column).write.format("parquet").bucketBy(buckets, column).sortBy(column).option("path", path).saveAsTable(table)
    return catalog.spark.table(table)


def write_delta(rt: DataFrame, path: str, files: int | None = None) -> None:
    """Runs with delta-coded starts, range-split by start."""
    n = files or max(1, math.ceil(rt.count() / FILE_RUNS))
    delta_options(_sorted(rt, n, "f").write).parquet(path)


def without_starts(rt: DataFrame, block: int) -> DataFrame:
    """Runs as arrays by block of starts: (blk, blk_start, v[], c[]); starts are implied."""
    rows = rt.withColumn("blk", F.expr(f"f div {block}")).groupBy("blk").agg(F.min("f").alias("blk_start"), F.array_sort(F.collect_list(F.struct("f", "v", "c"))).alias("x"))
    return rows.select("blk", "blk_start", F.transform("x", lambda r: r["v"]).alias("v"), F.transform("x", lambda r: r["c"]).alias("c"))


def rebuild_starts(blocks: DataFrame) -> DataFrame:
    """(f, v, c) from block arrays; f is the running sum of counts inside a block."""
    rows = blocks.select("blk", "blk_start", F.posexplode(F.arrays_zip("v", "c")).alias("i", "x")).select("blk", "blk_start", "i", "x.v", "x.c")
    w = Window.partitionBy("blk").orderBy("i").rowsBetween(Window.unboundedPreceding, -1)
    return rows.select((F.col("blk_start") + F.coalesce(F.sum("c").over(w), F.lit(0))).alias("f"), "v", "c")
