"""Queries whose comparisons are on columns deep in the sort: intersecting independent seeks, and the alternatives."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runstore.operators import bandjoin, runs
from runstore.plans import collapse
from runstore.sources import layout
from runstore.spec import Pred, RunTable, SortedProjection


def _seek(catalog, p: SortedProjection, preds: tuple[Pred, ...], by_value: bool) -> dict[str, DataFrame]:
    """Qualifying runs of each compared column."""
    tables, out = runs.build_runs(catalog, p), {}
    for c in sorted({x.col for x in preds}, key=p.depth):
        mine = tuple(x for x in preds if x.col == c)
        if by_value:
            df = layout.read_by_value(catalog, tables[c], mine)
        else:
            df = tables[c].frame
            for x in mine:
                df = df.where(x.on(F.col("v")))
        out[c] = df.select("f", "c", F.col("v").alias(c))
    return out


def fetch_columns(catalog, hits: DataFrame, p: SortedProjection, cols: tuple[str, ...], deepest: str, block: int | None) -> DataFrame:
    """Hits (runs of column `deepest`) with the values of other columns: ancestors by containment of the hit, deeper ones by their own starts."""
    tables = runs.build_runs(catalog, p)
    have = set(hits.columns)
    for c in cols:
        if c in have:
            continue
        rt = tables[c].frame.select("f", "c", F.col("v").alias(c))
        if p.depth(c) < p.depth(deepest):
            size = block_for(tables[c]) if block is None else block
            hits = bandjoin.containment_join(rt, hits, "broadcast_block", size, tables[c].runs + tables[c].rows // size + 1)
        else:
            hits = bandjoin.containment_join(hits, rt, "copartition", block or bandjoin.BLOCK)
    return hits


def block_for(outer: RunTable) -> int:
    """A block of about 16 outer runs, so that an inner run meets few of them whatever their length."""
    return 1 << max(4, math.ceil(math.log2(16 * max(1, outer.rows) / max(1, outer.runs))))


def intersect_seeks(catalog, p: SortedProjection, preds: tuple[Pred, ...], cols: tuple[str, ...], by_value: bool = True, block: int | None = None) -> DataFrame:
    """Seek each compared column by value, intersect the hits by containment, fetch the rest."""
    found = _seek(catalog, p, preds, by_value)
    order = list(found)
    hits = found[order[0]]
    for c in order[1:]:
        hits = bandjoin.containment_join(hits, found[c], "copartition", block or block_for(runs.build_runs(catalog, p)[order[0]]))
    return layout.copies(fetch_columns(catalog, hits, p, cols, order[-1], block), cols)


def late_materialize(catalog, p: SortedProjection, preds: tuple[Pred, ...], cols: tuple[str, ...], block: int | None = None) -> DataFrame:
    """Scan the compared columns in full, join positions, fetch the rest."""
    return intersect_seeks(catalog, p, preds, cols, by_value=False, block=block)


def skip_scan(catalog, p: SortedProjection, preds: tuple[Pred, ...], cols: tuple[str, ...], block: int | None = None) -> DataFrame:
    """For each combination of the columns before, seek the compared one inside it.

    Combinations are the runs found so far; a compared column is read from its
    copy by value, and while few combinations are left, inside their positions
    only (literals that prune the scan).  The others carry their values along.
    """
    tables = runs.build_runs(catalog, p)
    compared = {x.col for x in preds}
    last = max((p.depth(c) for c in (*compared, *cols)))
    df, before = None, None
    for c in p.sort_cols[:last]:
        if c not in compared and c not in cols and df is not None:
            continue
        rt, mine = tables[c], tuple(x for x in preds if x.col == c)
        found = layout.read_by_value(catalog, rt, mine) if mine else rt.frame
        if df is not None and mine and (spans := collapse.collapse_spans(df, collapse.FEW)):
            found = found.where(layout.inside(spans))
        found = found.select("f", "c", F.col("v").alias(c))
        size = block_for(before) if before is not None and block is None else block or bandjoin.BLOCK
        df = found if df is None else bandjoin.containment_join(df, found, "broadcast_block", size, before.runs + before.rows // size + 1)
        before = rt
    return layout.copies(df, cols)
