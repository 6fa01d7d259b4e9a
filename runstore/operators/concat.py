"""Merging run streams of several columns into one stream of segments (shallow orders)."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runstore.operators import bandjoin

BLOCK = 1 << 12


def _cut(df: DataFrame, block: int) -> DataFrame:
    """Runs cut at block borders: (blk, f, end, v)."""
    df = bandjoin.spread_over_blocks(df, "f", "c", block, "blk")
    lo = F.greatest("f", F.col("blk") * block)
    hi = F.least(F.col("f") + F.col("c"), (F.col("blk") + 1) * block)
    return df.select("blk", lo.alias("f"), hi.alias("end"), "v")


def concat_runs(tables: dict[str, DataFrame], block: int = BLOCK) -> DataFrame:
    """Segments (f, c, one column per table) of tilings of the same positions; one window per block, no join.

    A segment starts wherever any column's run starts; values carry forward.
    """
    names = list(tables)
    cut = [_cut(df, block).select("blk", "f", "end", *[F.when(F.lit(n == m), F.struct(F.col("v"))).alias(m) if n == m else F.lit(None).cast(f"struct<v:{dict(tables[m].dtypes)['v']}>").alias(m) for m in names]) for n, df in tables.items()]
    starts = reduce(DataFrame.union, cut).groupBy("blk", "f").agg(F.max("end").alias("end"), *[F.first(m, ignorenulls=True).alias(m) for m in names])
    w = Window.partitionBy("blk").orderBy("f")
    upto = w.rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("blk")
    nxt = F.coalesce(F.lead("f").over(w), F.max("end").over(whole))
    out = starts.select("f", (nxt - F.col("f")).alias("c"), *[F.last(m, ignorenulls=True).over(upto).alias(m) for m in names])
    return out.select("f", "c", *[F.col(f"{m}.v").alias(m) for m in names])


def concat_by_function(a: DataFrame, b: DataFrame, names: tuple[str, str], block: int = BLOCK) -> DataFrame:
    """The same for two tables by a table function per block (cogrouped pandas): the form the native one is compared with."""
    x, y = _cut(a, block), _cut(b, block)
    kinds = [dict(t.dtypes)["v"] for t in (a, b)]

    def merge(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        left, right = left.sort_values("f"), right.sort_values("f")
        starts = pd.DataFrame({"f": sorted({*left["f"], *right["f"]})})
        end = max(left["end"].max(), right["end"].max())
        got = pd.merge_asof(starts, left[["f", "v"]].rename(columns={"v": names[0]}), on="f")
        got = pd.merge_asof(got, right[["f", "v"]].rename(columns={"v": names[1]}), on="f")
        got["c"] = got["f"].shift(-1, fill_value=end) - got["f"]
        return got[["f", "c", *names]]

    return x.groupBy("blk").cogroup(y.groupBy("blk")).applyInPandas(merge, f"f long, c long, {names[0]} {kinds[0]}, {names[1]} {kinds[1]}")
