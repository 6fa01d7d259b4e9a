"""Materialized views without parameters: definition, merging, matching, answering, maintenance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from runstore.functions.aggs import is_money, plain
from runstore.spec import MONEY, Agg, StarQuery, ViewDefinition, joined

#: How an aggregate over groups is made from the same aggregate of finer groups.
MERGE = {"count": "sum", "sum": "sum", "min": "min", "max": "max"}


def materialize(catalog, answer: DataFrame, name: str) -> DataFrame:
    """One query's answer, stored: it serves that query with its own constants only."""
    return catalog.stored(answer, name)


def generalize(q: StarQuery, name: str) -> ViewDefinition:
    """The view that serves the query for any constants: compared columns become groups."""
    groups = dict.fromkeys((*[p.col for p in q.preds], *q.columns))
    return ViewDefinition(name, q.base, q.joins, tuple(groups), q.aggs)


def merge_definitions(defs: list[ViewDefinition]) -> list[ViewDefinition]:
    """Definitions of equal joins and groups become one with all their aggregates."""
    out: list[ViewDefinition] = []
    for d in defs:
        for k, o in enumerate(out):
            if (o.base, set(o.joins), set(o.groups)) == (d.base, set(d.joins), set(d.groups)):
                aggs = dict.fromkeys((*o.aggs, *d.aggs))
                out[k] = ViewDefinition(f"{o.name}{d.name.removeprefix('v')}", o.base, o.joins, o.groups, tuple(aggs))
                break
        else:
            out.append(d)
    return out


def _finest(a: Agg, kind: str) -> F.Column:
    """An aggregate as the view stores it: money stays decimal, so that it can be added to."""
    if a.fn == "sum" and is_money(a.col, kind):
        return F.sum(F.col(a.col).cast(MONEY)).alias(a.alias)
    return plain(a, kind)


def build_view(catalog, v: ViewDefinition) -> DataFrame:
    """The view's rows, stored in the order of its leading group."""
    def build() -> DataFrame:
        rows = joined(catalog, v.base, v.joins)
        kinds = dict(rows.dtypes)
        return _stored(catalog, v, rows.groupBy(*v.groups).agg(*[_finest(a, kinds.get(a.col, "")) for a in v.aggs]))

    return catalog.made(("view", v), build)


def _stored(catalog, v: ViewDefinition, rows: DataFrame) -> DataFrame:
    return catalog.stored(rows.repartitionByRange(v.groups[0]).sortWithinPartitions(*v.groups), v.name)


def materialize_exact(catalog, q: StarQuery, name: str) -> DataFrame:
    """The answer of one query with its constants, stored; the router serves that very query from it."""
    return catalog.made(("exact", ViewDefinition(name, q.base, q.joins, q.columns, q.aggs), q), lambda: materialize(catalog, answer(joined(catalog, q.base, q.joins), q), name))


def answer(df: DataFrame, q: StarQuery) -> DataFrame:
    """The query's filter, grouping and aggregates over (joined) rows."""
    kinds = dict(df.dtypes)
    for p in q.preds:
        df = df.where(p.on(F.col(p.col)))
    if q.aggs:
        df = df.groupBy(*q.columns).agg(*[plain(a, kinds.get(a.col, "")) for a in q.aggs])
    else:
        df = df.select(*q.columns)
    df = df.orderBy(*q.order) if q.order else df
    return df.limit(q.limit) if q.limit is not None else df


def match_view(q: StarQuery, v: ViewDefinition) -> str:
    """Why the view cannot answer the query; empty if it can."""
    if q.base != v.base or set(q.joins) != set(v.joins):
        return "other tables"
    if lost := ({p.col for p in q.preds} | set(q.columns)) - set(v.groups):
        return f"not grouped by {', '.join(sorted(lost))}"
    if not q.aggs:
        return "no aggregate"
    have = {(a.fn, a.col) for a in v.aggs}
    for a in q.aggs:
        if a.fn not in MERGE:
            return f"{a.fn} cannot be merged"
        if (a.fn, a.col) not in have:
            return f"no {a.fn} of {a.col or 'rows'}"
    return ""


def answer_from_view(catalog, q: StarQuery, v: ViewDefinition, reaggregate: bool = False) -> DataFrame:
    """The query from the view's rows; regrouped only if the filtered groups are not the query's already."""
    if why := match_view(q, v):
        raise ValueError(f"{v.name}: {why}")
    df = build_view(catalog, v)
    for p in q.preds:
        df = df.where(p.on(F.col(p.col)))
    source = {(a.fn, a.col): a.alias for a in v.aggs}
    fixed = {p.col for p in q.preds if p.op == "="}

    def out(c: Column, a: Agg) -> Column:
        if a.fn == "count":
            c = F.coalesce(c, F.lit(0).cast("long"))  # a count over no rows is none
        return (c.cast("double") if a.fn == "sum" and "decimal" in kinds[source[a.fn, a.col]] else c).alias(a.alias)

    kinds = dict(df.dtypes)
    if not reaggregate and q.columns and set(v.groups) - fixed == set(q.columns) - fixed:
        df = df.select(*q.columns, *[out(F.col(source[a.fn, a.col]), a) for a in q.aggs])
    else:
        df = df.groupBy(*q.columns).agg(*[out(getattr(F, MERGE[a.fn])(source[a.fn, a.col]), a) for a in q.aggs])
    df = df.orderBy(*q.order) if q.order else df
    return df.limit(q.limit) if q.limit is not None else df


def derive_view(catalog, v: ViewDefinition, groups: tuple[str, ...]) -> DataFrame:
    """A coarser view from a finer one."""
    df = build_view(catalog, v)
    return df.groupBy(*groups).agg(*[getattr(F, MERGE[a.fn])(a.alias).alias(a.alias) for a in v.aggs])


def merged(v: ViewDefinition, view: DataFrame, delta: DataFrame) -> DataFrame:
    """The view with inserted rows' groups added. Both have the view's columns."""
    both, kinds = view.unionByName(delta), dict(view.dtypes)
    # of the view's own types: a sum of decimals would get wider with every merge
    return both.groupBy(*v.groups).agg(*[getattr(F, MERGE[a.fn])(a.alias).cast(kinds[a.alias]).alias(a.alias) for a in v.aggs])


def delta_of(v: ViewDefinition, rows: DataFrame) -> DataFrame:
    """New (already joined) rows, grouped as the view is."""
    kinds = dict(rows.dtypes)
    return rows.groupBy(*v.groups).agg(*[_finest(a, kinds.get(a.col, "")) for a in v.aggs])


def refresh(v: ViewDefinition, view: DataFrame, inserts: DataFrame | None = None, deletes: DataFrame | None = None, remaining: DataFrame | None = None) -> DataFrame:
    """The view after inserts and deletes of (joined) rows.

    Counts and sums are subtracted; groups that lose a row and hold MIN or MAX
    are made anew from `remaining` (all rows left), and groups without rows go.
    A view without COUNT(*) is made anew in the touched groups as well.
    """
    if inserts is not None:
        view = merged(v, view, delta_of(v, inserts))
    if deletes is None:
        return view
    counted = next((a.alias for a in v.aggs if a.fn == "count" and a.col is None), None)
    if counted and all(a.fn in ("count", "sum") for a in v.aggs):
        less = delta_of(v, deletes)
        less = less.select(*v.groups, *[(-F.col(a.alias)).alias(a.alias) for a in v.aggs])
        return merged(v, view, less).where(F.col(counted) > 0)
    touched = deletes.select(*v.groups).distinct()
    on = lambda x, y: [x[g].eqNullSafe(y[g]) for g in v.groups]
    kept = view.join(touched, on(view, touched), "left_anti")
    again = remaining.join(touched, on(remaining, touched), "left_semi")
    return kept.unionByName(delta_of(v, again))


def apply_change(catalog, table: str, inserts: DataFrame | None = None, deletes: DataFrame | None = None, key: tuple[str, ...] = (), definitions: list[ViewDefinition] = ()) -> None:
    """Change a base table and bring the stored views on it up to date; run tables on it are made anew when next asked for.

    inserts: rows of the table; deletes: rows to go, found by the columns of `key`.
    A view whose other tables did not change is refreshed from the changed rows alone and stored again.
    """
    old = catalog.table(table)
    gone = None if deletes is None else old.join(deletes.select(*key).distinct(), list(key), "left_semi")
    now = old if deletes is None else old.join(deletes.select(*key).distinct(), list(key), "left_anti")
    now = now if inserts is None else now.unionByName(inserts)
    now = catalog.stored(now, f"table-{table}")
    kept = {v.name: build_view(catalog, v) for v in definitions if v.base == table}
    gone = None if gone is None else catalog.stored(gone, f"gone-{table}")
    fixed = {t: catalog.table(t) for v in definitions for t in [j.table for j in v.joins]}

    class Changed:
        """The tables as a view's joins see them: the base replaced by some of its rows."""

        def __init__(self, rows: DataFrame):
            self.rows = rows

        def table(self, name: str) -> DataFrame:
            return self.rows if name == table else fixed[name]

    rows_of = lambda v, rows: None if rows is None else joined(Changed(rows), v.base, v.joins)
    catalog.replace(table, now)
    for v in definitions:
        if v.name in kept:
            fresh = refresh(v, kept[v.name], rows_of(v, inserts), rows_of(v, gone), rows_of(v, now))
            catalog.keep(("view", v), _stored(catalog, v, fresh), v)
