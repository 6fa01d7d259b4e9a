"""Operator 3: proportional stratified interleaving of documents into shards.

Within each source rows are put in a seeded random order (md5 of seed and id)
and numbered 1..n; the row numbered r gets the fraction (2r - 1) / 2n.  Rows of
all sources sorted by that fraction form one sequence in which every stretch
has the sources in their overall proportions, and cutting it into equal
stretches gives shards that match the mixture.  Law `rows`: shard sizes are at
most one apart; a slot is the row's place in its shard.

No rank is taken in one task.  A random order is uniform, so equal stretches of
it (by the leading digits of the hash within a source, by the fraction over
all) hold near equal numbers of rows: rows are numbered within their stretch
and the stretches' counts, summed up in order, are added.  A source that holds
any share of the rows has that share of the stretches.  Only ids, sizes and
sums are shuffled, not texts.

Nulls: a null text has no bytes (size 1); null sources are one source; null ids
are ordered by text sum.  Rows that agree in id, source, size and sum are
interchangeable, each gets its own place.  An empty table gives no rows.
Other columns of the input are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from runstore.llm import base

#: Rows of a stretch at least; beyond its square stretches grow with the root of the rows.
STRETCH_ROWS = 1_000


def _numbered(df: DataFrame, keys: list[str], stretch: str, order: list[Column], out: str) -> DataFrame:
    """df with `out`: the row's number from 0 within keys, in the order of (stretch, order)."""
    counts = df.groupBy(*keys, stretch).agg(F.count("*").alias("_n"))
    within = Window.partitionBy(*[F.col(k) for k in keys] or [F.lit(0)]).orderBy(stretch)
    before = counts.select(*keys, stretch, (F.sum("_n").over(within) - F.col("_n")).alias("_before"))
    inner = df.withColumn("_k", F.row_number().over(Window.partitionBy(*keys, stretch).orderBy(*order)))
    a, b = inner.alias("a"), before.alias("b")
    on = [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in [*keys, stretch]]
    return a.join(b, on).select("a.*", (F.col("_before") + F.col("_k") - 1).alias(out)).drop("_k")


def interleave(docs: DataFrame, shards: int, seed: int = 7, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text") -> DataFrame:
    """One row per document: id, source, size, text_crc32, fraction, position, shard, slot."""
    if shards < 1:
        raise ValueError("shards must be positive")
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(source_col).cast("string").alias("source"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("null"))).cast("binary")).alias("shuffled"),
    )
    rows = base.stored(rows, "interleave")
    sizes = rows.groupBy("source").agg(F.count("*").alias("n_source"))
    total = sizes.agg(F.sum("n_source")).first()[0] or 0
    stretch_rows = max(STRETCH_ROWS, math.isqrt(total))
    s = base.checked_broadcast(sizes).alias("s")
    rows = rows.alias("r").join(s, F.col("r.source").eqNullSafe(F.col("s.source"))).select("r.*", "n_source")
    unit = F.conv(F.substring("shuffled", 1, 12), 16, 10).cast("double") / F.lit(float(16**12))
    rows = rows.withColumn("stretch", F.floor(unit * F.ceil(F.col("n_source") / F.lit(stretch_rows))).cast("long"))
    order = [F.col("shuffled"), F.col("doc_id"), F.col("text_crc32"), F.col("size")]
    rows = _numbered(rows, ["source"], "stretch", order, "rank")
    rows = rows.withColumn("fraction", (2 * F.col("rank") + 1) / (2 * F.col("n_source"))).drop("stretch")
    stretches = max(1, math.ceil(total / stretch_rows))
    rows = rows.withColumn("stretch", F.floor(F.col("fraction") * F.lit(stretches)).cast("long"))
    rows = _numbered(rows, [], "stretch", [F.col("fraction"), F.col("source"), *order], "position")
    # in whole numbers: the shard of a position p is p * shards div total
    shard = F.expr(f"cast((cast(position as decimal(38,0)) * {shards}) div {max(1, total)} as int)")
    rows = rows.withColumn("shard", shard)
    first = F.expr(f"cast((cast(shard as decimal(38,0)) * {total} + {shards - 1}) div {shards} as long)")
    return rows.select("doc_id", "source", "size", "text_crc32", "fraction", "position", "shard", (F.col("position") - first).alias("slot"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = interleave(base.table(spark, sf_dir, "documents"), 8)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
