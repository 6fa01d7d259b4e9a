"""Containment joins of run tables: the inner runs that start inside an outer run.

`outer` has (f, c) and any value columns, `inner` has (f) and any others; the
two share no other column.  The result has the inner's columns and the outer's
without f, c.  Ranges are inclusive: outer.f <= inner.f <= outer.f + outer.c - 1.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from runstore.sources import layout

#: Outer runs that may be broadcast, by count.
BROADCAST_RUNS = 1_000_000
BLOCK = 1 << 12
_STEP = 1 << 16
STRATEGIES = ("nl", "broadcast_block", "copartition", "parent", "probe", "asof", "crossrow")


def _tagged(outer: DataFrame) -> DataFrame:
    return outer.withColumnRenamed("f", "_of").withColumnRenamed("c", "_oc")


def _inside() -> F.Column:
    return F.col("f").between(F.col("_of"), F.col("_of") + F.col("_oc") - 1)


def spread_over_blocks(df: DataFrame, f: str, c: str, block: int, out: str) -> DataFrame:
    """Runs once for each block of positions they touch, in two steps so that no array is longer than `_STEP` blocks."""
    first, last = F.expr(f"{f} div {block}"), F.expr(f"({f} + {c} - 1) div {block}")
    df = df.withColumn("_s", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((last - first) / _STEP))))
    lo = first + F.col("_s") * _STEP
    return df.withColumn(out, F.explode(F.sequence(lo, F.least(last, lo + _STEP - 1)))).drop("_s")


def _cut(outer: DataFrame, block: int) -> DataFrame:
    """Outer runs once for each block of positions they touch."""
    return spread_over_blocks(_tagged(outer), "_of", "_oc", block, "_blk")


def touched(outer: DataFrame, block: int) -> int:
    """Rows of `_cut`, without making them."""
    return outer.agg(F.sum(F.expr(f"(f + c - 1) div {block} - f div {block} + 1"))).first()[0] or 0


def containment_join(outer: DataFrame, inner: DataFrame, strategy: str, block: int = BLOCK, most: int | None = None) -> DataFrame:
    """most: a bound of the outer's rows after they are spread over blocks, where one is known; else they are counted.

    What a strategy would hold in every task is counted first; over `BROADCAST_RUNS` rows the join shuffles instead.
    """
    keep = [*inner.columns, *[c for c in outer.columns if c not in ("f", "c")]]
    if strategy in ("nl", "crossrow", "probe", "broadcast_block"):
        n = most if most is not None else touched(outer, block) if strategy == "broadcast_block" else outer.count()
        if n > BROADCAST_RUNS:
            strategy = "copartition"
    if strategy == "nl":
        out = inner.join(F.broadcast(_tagged(outer)), _inside())
    elif strategy == "crossrow":
        out = inner.crossJoin(F.broadcast(_tagged(outer))).where(_inside())
    elif strategy in ("broadcast_block", "copartition"):
        cut = _cut(outer, block)
        cut = F.broadcast(cut) if strategy == "broadcast_block" else cut.hint("merge")
        out = inner.withColumn("_b", F.expr(f"f div {block}")).join(cut, (F.col("_b") == F.col("_blk")) & _inside())
    elif strategy == "parent":
        out = inner.join(_tagged(outer).drop("_oc"), F.col("parent_f") == F.col("_of"))
    elif strategy == "asof":
        return _asof(outer, inner, keep, block)
    elif strategy == "probe":
        return _probe(outer, inner, keep)
    else:
        raise ValueError(f"unknown containment join {strategy}")
    return out.select(*keep)


def bucketed_join(catalog, outer: DataFrame, inner: DataFrame, block: int = BLOCK, buckets: int = 8) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(the containment join, and both sides as stored): sides bucketed by block once, then joined without a shuffle as often as asked for."""
    o = layout.write_bucketed(catalog, _cut(outer, block), "outer_runs", "_blk", buckets)
    i = layout.write_bucketed(catalog, inner.withColumn("_b", F.expr(f"f div {block}")), "inner_runs", "_b", buckets)
    keep = [*inner.columns, *[c for c in outer.columns if c not in ("f", "c")]]
    return i.join(o.hint("merge"), (F.col("_b") == F.col("_blk")) & _inside()).select(*keep), o, i


def _asof(outer: DataFrame, inner: DataFrame, keep: list[str], block: int) -> DataFrame:
    """Both sides in order within a block; the last outer run carries forward."""
    values = [c for c in outer.columns if c not in ("f", "c")]
    o = _cut(outer, block).select(F.col("_blk"), F.greatest("_of", F.col("_blk") * block).alias("_at"), F.lit(0).alias("_kind"), F.struct("_of", "_oc", *values).alias("_o"), F.lit(None).cast(inner.schema).alias("_i"))
    i = inner.select(F.expr(f"f div {block}").alias("_blk"), F.col("f").alias("_at"), F.lit(1).alias("_kind"), F.lit(None).cast(o.schema["_o"].dataType).alias("_o"), F.struct(*inner.columns).alias("_i"))
    w = Window.partitionBy("_blk").orderBy("_at", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    got = o.union(i).withColumn("_o", F.last("_o", ignorenulls=True).over(w)).where("_kind = 1 and _o is not null")
    return got.select("_i.*", "_o.*").where(_inside()).select(*keep)


def _probe(outer: DataFrame, inner: DataFrame, keep: list[str]) -> DataFrame:
    """Binary search of each inner start in the sorted outer starts, a counted table held by every task."""
    values = [c for c in outer.columns if c not in ("f", "c")]
    table = outer.orderBy("f").toArrow()
    schema = inner.select(*inner.columns).join(outer.select(*values).limit(0), how="cross").select(*keep).schema
    arrow = to_arrow_schema(schema)
    starts, sizes = table["f"].to_numpy(), table["c"].to_numpy()
    at_f = inner.columns.index("f")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            f = batch.column(at_f).to_numpy()
            k = np.searchsorted(starts, f, side="right") - 1
            hit = (k >= 0) & (f < starts[k] + sizes[k]) if len(starts) else np.zeros(len(f), bool)
            took = table.select(values).take(pa.array(k[hit])).combine_chunks()
            mine = batch.filter(pa.array(hit))
            columns = [*mine.columns, *[c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in took.columns]]
            yield pa.RecordBatch.from_arrays([c.cast(t.type) for c, t in zip(columns, arrow)], schema=arrow)

    return inner.mapInArrow(run, schema)


def overlap_join(a: DataFrame, b: DataFrame, block: int = BLOCK) -> DataFrame:
    """Pairs of runs (f, c, value columns) of two tilings that share positions, with f, c of what they share.

    Each pair meets in the block of the later start only, so none is doubled.
    """
    def cut(df: DataFrame, p: str) -> DataFrame:
        df = df.withColumnRenamed("f", f"{p}f").withColumnRenamed("c", f"{p}c")
        return spread_over_blocks(df, f"{p}f", f"{p}c", block, f"{p}blk")

    x, y = cut(a, "_a"), cut(b, "_b")
    lo = F.greatest("_af", "_bf")
    hi = F.least(F.col("_af") + F.col("_ac"), F.col("_bf") + F.col("_bc"))
    met = x.join(y, (F.col("_ablk") == F.col("_bblk")) & (lo < hi) & (F.col("_ablk") == F.floor(lo / block)))
    values = [c for c in (*a.columns, *b.columns) if c not in ("f", "c")]
    return met.select(lo.alias("f"), (hi - lo).alias("c"), *values)
