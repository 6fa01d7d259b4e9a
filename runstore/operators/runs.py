"""Building run tables, reading rows back from them, and checks of their shape."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runstore.catalog import Catalog
from runstore.operators import positions
from runstore.sources import layout
from runstore.spec import RunTable, SortedProjection


def prefix_tables(catalog, p: SortedProjection) -> list[DataFrame]:
    """For depth 1..k the distinct sort prefixes with start f and length c; each is rolled up from the next deeper one."""

    def build() -> list[DataFrame]:
        cols = list(p.sort_cols)
        counts = p.frame(catalog).groupBy(*cols).agg(F.count("*").alias("c"))
        deepest = catalog.stored(positions.prefix_starts(catalog, counts, cols).select(*cols, "f", "c"), f"{p.name}-prefix")
        tables = [deepest]
        for k in range(len(cols) - 1, 0, -1):
            up = tables[0].groupBy(*cols[:k]).agg(F.min("f").alias("f"), F.sum("c").alias("c"))
            tables.insert(0, catalog.stored(up, f"{p.name}-prefix"))
        return tables

    return catalog.made(("prefixes", p), build)


def prefix_rollup(catalog, p: SortedProjection) -> DataFrame:
    """All prefix groupings in one frame: depth, the columns (null below the depth), f, c."""
    cols = list(p.sort_cols)
    parts = [t.select(F.lit(k + 1).alias("depth"), *[F.col(c) if i <= k else F.lit(None).cast(t0).alias(c) for i, (c, t0) in enumerate(types)], "f", "c") for k, t, types in _typed(catalog, p, cols)]
    return reduce(DataFrame.unionByName, parts)


def _typed(catalog, p: SortedProjection, cols: list[str]):
    tables = prefix_tables(catalog, p)
    types = [(c, dict(tables[-1].dtypes)[c]) for c in cols]
    return [(k, t, types) for k, t in enumerate(tables)]


def build_runs(catalog, p: SortedProjection) -> dict[str, RunTable]:
    """Run tables of all columns of an aligned projection, written by start and by value.

    Null is a value like any other.  Each row also carries parent_f, the start
    of the run of the next shallower column that holds it.
    """

    def build() -> dict[str, RunTable]:
        out, manifest = {}, []
        tables = prefix_tables(catalog, p)
        n = tables[0].agg(F.sum("c")).first()[0] or 0
        for k, col in enumerate(p.sort_cols):
            t = tables[k].alias("t")
            if k:
                up = tables[k - 1].select(*p.sort_cols[:k], F.col("f").alias("parent_f")).alias("u")
                t = t.join(up, [F.col(f"t.{c}").eqNullSafe(F.col(f"u.{c}")) for c in p.sort_cols[:k]])
            else:
                t = t.withColumn("parent_f", F.lit(1).cast("long"))
            rt = t.select(F.col("t.f").alias("f"), F.col(f"t.{col}").alias("v"), F.col("t.c").alias("c"), "parent_f")
            runs = tables[k].count()
            kind = layout.choose(n, runs, dict(rt.dtypes)["v"])
            out[col] = layout.write(catalog, rt, p.name, col, k + 1, kind, n, runs, p.delta)
            manifest.append({"projection": p.name, "column": col, "depth": k + 1, "layout": kind, "n_rows": n, "n_runs": runs, "path": out[col].path})
        path = catalog.save_manifest(p.name, manifest)
        for t in out.values():
            t.manifest = path
        return out

    return catalog.made(("runs", p), build)


def build_unaligned(catalog, p: SortedProjection, block: int = 1 << 16) -> dict[str, DataFrame]:
    """Unbroken runs (f, v, c) of stored columns in the projection's order, by breaks within blocks stitched at their borders."""

    def build() -> dict[str, DataFrame]:
        rows = p.frame(catalog).select(*dict.fromkeys((*p.sort_cols, *p.stored)))
        placed = catalog.stored(positions.assign_positions(catalog, rows, list(p.sort_cols)).select("pos", *p.stored), f"{p.name}-rows")
        return {c: catalog.stored(unbroken_runs(placed.select("pos", F.col(c).alias("v")), block, catalog), f"{p.name}-{c}") for c in p.stored}

    return catalog.made(("unaligned", p), build)


def _carried(catalog, ends: DataFrame) -> DataFrame:
    """Rows (blk, cont, carried): the start of the run that is open when a block begins.

    Blocks are range-split; each part hands its last open start to those after
    it (one number a part reaches the driver), inside a part a window carries it.
    """
    parts = catalog.stored(ends.repartitionByRange("blk").withColumn("_p", F.spark_partition_id()), "block-ends")
    last = dict(parts.where("open is not null").groupBy("_p").agg(F.max_by("open", "blk")).collect())
    rows, at = [], None
    for p in range((max(last) if last else 0) + 2):
        rows.append((p, at))
        at = last.get(p, at)
    top = len(rows) - 1
    into = catalog.spark.createDataFrame(rows, "_p int, _at long")
    w = Window.partitionBy("_p").orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.withColumn("_own", F.last("open", ignorenulls=True).over(w)).withColumn("_p", F.least("_p", F.lit(top)))
    return parts.join(F.broadcast(into), "_p").select("blk", "cont", F.coalesce("_own", "_at").alias("carried"))


def unbroken_runs(rows: DataFrame, block: int, catalog: Catalog | None = None) -> DataFrame:
    """Maximal runs (f, v, c) of rows (pos, v)."""
    catalog = catalog or Catalog(rows.sparkSession, "")
    rows = rows.withColumn("blk", F.expr(f"pos div {block}"))
    w = Window.partitionBy("blk").orderBy("pos")
    first = F.row_number().over(w) == 1
    rows = rows.withColumn("new", (first | ~F.col("v").eqNullSafe(F.lag("v").over(w))).cast("int"))
    rows = rows.withColumn("g", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    part = rows.groupBy("blk", "g").agg(F.min("pos").alias("f"), F.first("v").alias("v"), F.count("*").alias("c"))
    # one row a block: its first and last run; a block's first run may continue the last one's before it
    ends = part.groupBy("blk").agg(F.min_by(F.struct("v", "f"), "g").alias("a"), F.max_by(F.struct("v", "f"), "g").alias("z"), F.count("*").alias("n"))
    before = ends.select((F.col("blk") + 1).alias("blk"), F.col("z").alias("y"))
    ends = ends.join(before, "blk", "left").withColumn("cont", F.col("y").isNotNull() & F.col("a.v").eqNullSafe(F.col("y.v")))
    ends = ends.withColumn("open", F.when(~F.col("cont") | (F.col("n") > 1), F.col("z.f"))).select("blk", "cont", "open")
    part = part.join(_carried(catalog, ends), "blk")
    start = F.when((F.col("g") == 1) & F.col("cont"), F.col("carried")).otherwise(F.col("f"))
    return part.groupBy(start.alias("f")).agg(F.first("v").alias("v"), F.sum("c").alias("c")).select("f", "v", "c")


def expand(rt: DataFrame) -> DataFrame:
    """One row (pos, v) for each position of a run table."""
    return layout.positions_of_runs(rt.select("f", "c", "v"))


def reconstruct(catalog, p: SortedProjection) -> DataFrame:
    """The projection's rows with their places `pos`, from its run tables alone.

    Runs nest, so each column's value is found at the start of the run above
    and only the deepest runs are expanded, at the end.  Expanded rows are
    never joined: the planner takes them to be as few as the runs they are
    made of, and would send them to all tasks through the driver.
    """
    tables = build_runs(catalog, p)
    *shallower, deepest = p.sort_cols
    rows = tables[deepest].frame.select("f", "c", F.col("v").alias(deepest), F.col("parent_f").alias("_up"))
    for c in reversed(shallower):
        at = tables[c].frame.select(F.col("f").alias("_up"), F.col("v").alias(c), F.col("parent_f").alias("_next"))
        rows = rows.join(at, "_up").drop("_up").withColumnRenamed("_next", "_up")
    return layout.positions_of_runs(rows.select("f", "c", *p.sort_cols))


def check_nesting(shallow: DataFrame, deep: DataFrame) -> DataFrame:
    """Starts of the shallow column that no deeper run starts at: empty if ranges nest."""
    return shallow.join(deep.select("f"), "f", "left_anti")


def check_tiling(rt: DataFrame) -> DataFrame:
    """Runs that do not start where the one before ends: empty if runs tile the positions."""
    ends = rt.select((F.col("f") + F.col("c")).alias("f"))
    return rt.where("f > 1").select("f").join(ends, "f", "left_anti")


def compact(segments: DataFrame, sort_cols: list[str], catalog) -> DataFrame:
    """One table of prefixes (cols, f, c) out of several segments' prefix counts (cols, c)."""
    total = segments.groupBy(*sort_cols).agg(F.sum("c").alias("c"))
    return positions.prefix_starts(catalog, total, sort_cols)
