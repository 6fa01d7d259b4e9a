"""Page and size models: exact, from run counts."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import functions as F

from runstore.operators import runs
from runstore.plans import baselines, collapse, rewrite, views
from runstore.sources import layout
from runstore.sources.layout import width
from runstore.spec import Pred, RunTable, SortedProjection, StarQuery, ViewDefinition


@dataclass(frozen=True)
class CostModel:
    page_bytes: int = 8192
    tuple_overhead: int = 9


def selectivity(rt: RunTable, pred: Pred) -> float:
    """Share of rows that pass, exact, from one scan of a (leading) run table."""
    kept = rt.frame.where(pred.on(F.col("v"))).agg(F.sum("c")).first()[0] or 0
    return kept / rt.rows if rt.rows else 0.0


def encoded_bytes(n_rows: int, n_runs: int, n_values: int, w: int) -> dict[str, int]:
    """Bytes of one column: plain, by runs, by dictionary, as one bitmap per value."""
    bits = max(1, math.ceil(math.log2(max(2, n_values))))
    return {
        "plain": n_rows * w,
        "rle": n_runs * (w + 4),
        "dictionary": -(-n_rows * bits // 8) + n_values * w,
        "bitmap": n_values * (-(-n_rows // 8) + w),
    }


def storage_bytes(rt: RunTable, kind: str, model: CostModel) -> dict[str, int]:
    """A run table's modelled bytes, without and with the row engine's bytes per tuple."""
    tuples = rt.rows if rt.layout == "points" else rt.runs
    bare = tuples * (8 + width(kind) + (0 if rt.layout == "points" else 8))
    return {"bare": bare, "with_overhead": bare + tuples * model.tuple_overhead}


def run_stats(catalog, p: SortedProjection) -> list[tuple]:
    """(projection, column, depth, rows, runs, runs per row) of each column."""
    return [(p.name, c, t.depth, t.rows, t.runs, t.runs / max(1, t.rows)) for c, t in runs.build_runs(catalog, p).items()]


def _row_bytes(kinds: list[tuple[str, str]], model: CostModel) -> int:
    return sum(width(k) for _, k in kinds) + model.tuple_overhead


def row_pages(catalog, q: StarQuery, model: CostModel) -> int:
    """Pages of whole tuples of every table that the query names."""
    total = 0
    for name in (q.base, *[j.table for j in q.joins]):
        df = catalog.table(name)
        n = catalog.count(name)
        total += math.ceil(n * _row_bytes(df.dtypes, model) / model.page_bytes)
    return total


def floor_pages(catalog, q: StarQuery, p: SortedProjection, model: CostModel) -> int:
    """Pages that any column plan must read: per needed column the better of runs and plain values within the confined span."""
    kinds = rewrite.column_kinds(catalog, p)
    total = 0
    for c, df in zip(rewrite.needed_columns(p, q), baselines.floor_scan(catalog, q, p)):
        n_runs, n_rows = df.agg(F.count("*"), F.sum("c")).first()
        sizes = encoded_bytes(n_rows or 0, n_runs, n_runs, width(kinds[c]))
        total += max(1, math.ceil(min(sizes["rle"], sizes["plain"]) / model.page_bytes))
    return total


def run_tuples(catalog, q: StarQuery, p: SortedProjection) -> int:
    """Run tuples that the floor's reads touch."""
    return sum(df.count() for df in baselines.floor_scan(catalog, q, p))


def outer_rows(catalog, q: StarQuery, p: SortedProjection, collapsing: bool) -> int:
    """Outer tuples that drive the inner access: the spans that are left where it collapses, else the qualifying leading runs."""
    lead = rewrite.needed_columns(p, q)[0]
    mine = tuple(x for x in q.preds if x.col == lead)
    if collapsing and collapse.may_collapse(p, q, lead):
        found = layout.read_by_value(catalog, runs.build_runs(catalog, p)[lead], mine)
        spans = collapse.collapse_spans(found, collapse.FEW)
        if spans is not None:
            return len(spans)
    return layout.read_by_value(catalog, runs.build_runs(catalog, p)[lead], tuple(x for x in q.preds if x.col == lead)).count()


def estimates(catalog, q: StarQuery, projection: SortedProjection | None, view: ViewDefinition | None, partly: SortedProjection | None = None) -> dict[str, float]:
    """Bytes that each way to answer a query moves: those its scans read and those of the rows that enter its joins and groups.

    All numbers are exact: run counts, rows of views and tables, and the share of
    rows that the comparison on a leading sort column keeps.  Scans of sorted
    tables are charged for the confined part only.
    """
    out = {}
    kinds = {c: k for t in (q.base, *[j.table for j in q.joins]) for c, k in catalog.table(t).dtypes}
    size = lambda cols: sum(width(kinds.get(c, "bigint")) for c in cols)
    n = catalog.count(q.base)
    keys = {q.base: {j.left_key for j in q.joins}, **{j.table: {j.right_key, *[k.left_key for k in q.joins]} for j in q.joins}}
    read = 0.0
    for t in (q.base, *[j.table for j in q.joins]):
        own = {c for c, _ in catalog.table(t).dtypes}
        read += catalog.count(t) * size(own & (q.needed | keys[t]))
    moved = n * size(q.needed)
    out["columnar"] = read + moved * (1 + len(q.joins))
    if view is not None:
        rows = catalog.made(("rows of", view), lambda: views.build_view(catalog, view).count())
        kept = _leading_share(catalog, view, q)
        groups = size(view.groups) + 8 * len(view.aggs)
        regroup = set(view.groups) - {x.col for x in q.preds if x.op == "="} != set(q.columns) - {x.col for x in q.preds if x.op == "="}
        out["views"] = rows * kept * groups * (2 if regroup else 1)
    if projection is not None:
        out["runs"] = _run_bytes(catalog, q, projection, size)
    if partly is not None:
        known = tuple(x for x in q.preds if x.col in partly.sort_cols)
        part = StarQuery(q.base, q.joins, known, tuple(sorted(set(q.columns) & set(partly.sort_cols)))[:1], ())
        # the runs only say which rows may qualify; these are fetched from the base all the same
        out["hybrid"] = _run_bytes(catalog, part, partly, size) + read + moved * (1 + len(q.joins)) * min(1.0, _share(catalog, partly, q) + 0.01)
    return out


def _share(catalog, p: SortedProjection, q: StarQuery) -> float:
    """Share of rows that the comparisons on the leading column keep."""
    share = 1.0
    for x in q.preds:
        if x.col == p.sort_cols[0]:
            share = min(share, catalog.made(("share", p, x.col, x.op, str(x.value)), lambda x=x: selectivity(runs.build_runs(catalog, p)[x.col], x)))
    return share


def _run_bytes(catalog, q: StarQuery, p: SortedProjection, size) -> float:
    tables, share, total, fixed = runs.build_runs(catalog, p), 1.0, 0.0, True
    cols = rewrite.needed_columns(p, q)
    for k, c in enumerate(cols):
        t = tables[c]
        tuples, w = (t.rows if t.layout == "points" else t.runs), 16 + size([c])
        mine = [x for x in q.preds if x.col == c]
        if k == 0 and c == p.sort_cols[0] and mine:
            share = _share(catalog, p, q)
            fixed = all(x.op == "=" for x in mine)
        elif fixed and mine and all(x.op == "=" for x in mine) and p.depth(c) == k + 1:
            share /= max(1, tables[c].runs / max(1, tables[cols[k - 1]].runs))
        else:
            fixed = False
        # each column is read within the span, and joined with the one before unless that was collapsed
        total += tuples * share * w
        if q.aggs and c == cols[-1] and cols != [p.sort_cols[0]]:
            total += tuples * share * w  # its runs enter the grouping (those of the leading column are groups already)
    return total


def _leading_share(catalog, v: ViewDefinition, q: StarQuery) -> float:
    """Share of a view's rows that the comparison on its leading group keeps (it is stored in that order)."""
    lead = [x for x in q.preds if x.col == v.groups[0]]
    if not lead:
        return 1.0

    def count() -> float:
        df = views.build_view(catalog, v)
        n = catalog.made(("rows of", v), df.count)
        for x in lead:
            df = df.where(x.on(F.col(x.col)))
        return df.count() / max(1, n)

    return catalog.made(("view share", v, *[(x.col, x.op, str(x.value)) for x in lead]), count)


def plain_rle_bytes(rt: RunTable, kind: str) -> int:
    """Bytes of the same column run-length encoded without starts and without bytes per tuple."""
    return rt.runs * (width(kind) + 4)


def q_error(estimate: float, actual: float) -> float:
    """How far a cardinality estimate is off, as a factor."""
    a, b = max(1.0, estimate), max(1.0, actual)
    return max(a / b, b / a)


def catalyst_rows(df) -> float | None:
    """Catalyst's own row estimate of a frame, if it has one."""
    count = df._jdf.queryExecution().optimizedPlan().stats().rowCount()
    return float(count.get().toString()) if count.isDefined() else None


def bitmap_bytes(df, col: str) -> int:
    """Bytes of real bitmaps (one per value and 32,768 rows) over positions `pos`."""
    per = df.groupBy(F.col(col), F.bitmap_bucket_number(F.col("pos")).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("pos"))).alias("m"))
    return per.agg(F.sum(F.length("m"))).first()[0] or 0
