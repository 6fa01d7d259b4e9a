"""Dense positions of rows, and starts of runs, without sorting all rows in one task."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _ordered_parts(catalog, df: DataFrame, order: list[str], name: str) -> tuple[DataFrame, Window]:
    """df range-split by order, stored with its part number `_p`, and the window of a part."""
    split = df.repartitionByRange(*[F.col(c) for c in order]).withColumn("_p", F.spark_partition_id())
    return catalog.stored(split, name), Window.partitionBy("_p").orderBy(*order)


def _with_offsets(catalog, df: DataFrame, weight: str) -> DataFrame:
    """df with `_before`: the weight of all earlier parts. One number a part reaches the driver."""
    totals = sorted((r["_p"], r["n"]) for r in df.groupBy("_p").agg(F.sum(weight).alias("n")).collect())
    before = [0, *accumulate(n for _, n in totals)]
    rows = [(p, b) for (p, _), b in zip(totals, before)]
    return df.join(F.broadcast(catalog.spark.createDataFrame(rows, "_p int, _before long")), "_p")


def assign_positions(catalog, df: DataFrame, order: list[str]) -> DataFrame:
    """df with `pos`, the dense 1-based place of each row in the order (all columns of it must break ties)."""
    parts, w = _ordered_parts(catalog, df.withColumn("_c", F.lit(1)), order, "positions")
    out = _with_offsets(catalog, parts, "_c")
    return out.withColumn("pos", F.row_number().over(w) + F.col("_before")).drop("_p", "_c", "_before")


def prefix_starts(catalog, counts: DataFrame, sort_cols: list[str]) -> DataFrame:
    """Distinct sort prefixes with their count `c`, with the start `f` of each: positions of runs, not rows."""
    parts, w = _ordered_parts(catalog, counts, sort_cols, "prefixes")
    out = _with_offsets(catalog, parts, "c")
    upto = F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, 0))
    return out.withColumn("f", F.col("_before") + upto - F.col("c") + 1).drop("_p", "_before")
