"""Span collapse: a set of runs that lie next to each other, replaced by one pair of literals.

The literals go through the driver on purpose: a scalar subquery would not
reach the Parquet scan, literals do, and prune its row groups.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runstore.spec import Pred, RunTable, Span, StarQuery, SortedProjection
from runstore.sources import layout


def is_contiguous(p: SortedProjection, q: StarQuery, col: str) -> bool:
    """Whether the runs of col that pass its comparisons are one stretch of positions.

    It is so at depth 1 for ranges, and deeper below equalities on all columns
    before; and it may be collapsed if col is not in the output, or under an
    equality (its value is then a literal), and not aggregated.
    """
    preds = [x for x in q.preds if x.col == col]
    if not preds or not all(x.contiguous for x in preds) or any(col in (a.col, a.by) for a in q.aggs):
        return False
    equal = lambda c: any(x.col == c and x.op == "=" for x in q.preds)
    return all(equal(c) for c in p.sort_cols[: p.depth(col) - 1]) and (col not in q.columns or equal(col))


def may_collapse(p: SortedProjection, q: StarQuery, col: str) -> bool:
    """Whether the runs of col that pass may be replaced by their positions, as one span or several.

    Its values must not be asked for, and all columns before are fixed by
    equalities (so that its runs are found in one stretch).
    """
    equal = lambda c: any(x.col == c and x.op == "=" for x in q.preds)
    asked = col in q.columns or any(col in (a.col, a.by) for a in q.aggs)
    return any(x.col == col for x in q.preds) and not asked and all(equal(c) for c in p.sort_cols[: p.depth(col) - 1])


def collapse_span(catalog, rt: RunTable, preds: tuple[Pred, ...], within: Span | None = None) -> Span | None:
    """The span of runs whose values pass (inside another span, if given); None if there are none."""
    df = layout.read_by_value(catalog, rt, preds)
    if within is not None:
        df = df.where(F.col("f").between(F.lit(within.lo), F.lit(within.hi)))
    lo, hi, n = df.agg(F.min("f"), F.max(F.col("f") + F.col("c") - 1), F.sum("c")).first()
    if lo is None:
        return None
    if n != hi - lo + 1:
        raise ValueError(f"runs of {rt.column} that pass are not one stretch")
    return Span(lo, hi)


#: Spans that are handed to a scan as literals.
FEW = 64


def collapse_spans(runs: DataFrame, most: int = 1000) -> list[Span] | None:
    """Qualifying runs (f, c) as few spans, for IN lists and the like; None if there are more than `most`.

    A span starts at a run that no other ends before, and ends at one that no
    other starts after: two anti-joins, and no order over all runs.
    """
    df = runs.select("f", (F.col("f") + F.col("c")).alias("after"))
    starts = df.select("f").join(df.select(F.col("after").alias("f")), "f", "left_anti")
    ends = df.select("after").join(df.select(F.col("f").alias("after")), "after", "left_anti")
    lows = [r[0] for r in starts.orderBy("f").limit(most + 1).collect()]
    if len(lows) > most:
        return None
    highs = [r[0] for r in ends.orderBy("after").limit(most + 1).collect()]
    return [Span(lo, hi - 1) for lo, hi in zip(lows, highs, strict=True)]
