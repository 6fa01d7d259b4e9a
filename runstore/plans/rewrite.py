"""Mechanical rewriting of a star query over run tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runstore.functions.aggs import exact, weighted
from runstore.operators import bandjoin, runs
from runstore.operators.deep import block_for
from runstore.plans import collapse
from runstore.sources import layout
from runstore.spec import RunTable, SortedProjection, Span, StarQuery


def needed_columns(p: SortedProjection, q: StarQuery) -> list[str]:
    """The projection's columns that the query needs, shallow to deep; others are skipped."""
    return [c for c in p.sort_cols if c in q.needed]


def column_kinds(catalog, p: SortedProjection) -> dict[str, str]:
    """SQL types of the projection's columns."""
    return catalog.made(("kinds", p), lambda: dict(p.frame(catalog).dtypes))


def _values(rt: RunTable, q: StarQuery, span: Span | list[Span] | None, keep_parent: bool) -> DataFrame:
    """Runs of one column in a span whose values pass, v renamed to the column."""
    df = layout.read_runs(rt, span)
    for x in q.preds:
        if x.col == rt.column:
            df = df.where(x.on(F.col("v")))
    return df.select("f", "c", F.col("v").alias(rt.column), *(["parent_f"] if keep_parent else []))


def _pick(outer_runs: int, adjacent: bool) -> str:
    """Equality of starts where the inner column lies right below; else blocks, broadcast while the outer's exact count allows."""
    if adjacent:
        return "parent"
    return "broadcast_block" if outer_runs <= bandjoin.BROADCAST_RUNS else "copartition"


def positions_of(catalog, q: StarQuery, p: SortedProjection, collapsing: bool = True, join: str | None = None) -> tuple[DataFrame, dict[str, object], Span | list[Span] | None] | None:
    """Qualifying runs of the deepest needed column with all needed values, values known as literals, and the span(s) they lie in.

    None if a collapsed span shows that nothing qualifies.  join `seek` reads the
    inner column at the outer runs' positions only (literals in the scan), as
    long as these are few; beyond that it is the block join.
    """
    tables = runs.build_runs(catalog, p)
    cols, span, literal = needed_columns(p, q), None, {}
    left = list(cols)
    while collapsing and len(left) > 1 and collapse.is_contiguous(p, q, left[0]):
        c = left.pop(0)
        mine = tuple(x for x in q.preds if x.col == c)
        span = collapse.collapse_span(catalog, tables[c], mine, span)
        if span is None:
            return None
        literal.update({x.col: x.value for x in mine if x.op == "="})
    if collapsing and len(left) > 1 and collapse.may_collapse(p, q, left[0]):
        # values that are not neighbours (IN, <>, LIKE): several spans, if they are few
        c = left[0]
        found = layout.read_by_value(catalog, tables[c], tuple(x for x in q.preds if x.col == c))
        spans = collapse.collapse_spans(found if span is None else found.where(layout.inside(span)), collapse.FEW)
        if spans == []:
            return None
        if spans:
            span, left = spans, left[1:]
    df, before = None, None
    for c in left:
        parent = before is not None and p.depth(c) == p.depth(before) + 1
        inner = _values(tables[c], q, span, parent)
        if df is None:
            df = inner
            if join == "seek" and any(x.col == c for x in q.preds):
                mine = tuple(x for x in q.preds if x.col == c)
                df = layout.read_by_value(catalog, tables[c], mine)
                df = (df if span is None else df.where(layout.inside(span))).select("f", "c", F.col("v").alias(c))
        else:
            outer = tables[before]
            how = join or _pick(outer.runs, parent)
            if how == "seek":
                if spans := collapse.collapse_spans(df.select("f", "c"), collapse.FEW):
                    span = spans
                    inner = _values(tables[c], q, span, parent)
                how = "broadcast_block"
            if how == "parent" and not parent:
                how = _pick(outer.runs, False)
            if how == "parent" and outer.runs <= bandjoin.BROADCAST_RUNS:
                df = F.broadcast(df)
            size = block_for(outer)
            df = bandjoin.containment_join(df, inner, how, size, outer.runs if how in ("nl", "crossrow", "probe") else outer.runs + outer.rows // size + 1)
            if parent:
                df = df.drop("parent_f")
        before = c
    return df, literal, span


def rewrite_runs(catalog, q: StarQuery, p: SortedProjection, collapsing: bool = True, join: str | None = None, plan: str = "hash") -> DataFrame:
    """The query's answer from run tables.

    plan: `hash` aggregates joined runs by value; `sortagg` and `eager`
    aggregate the innermost column by its parent's run first, `sortagg` in the
    order a merge join delivers.
    """
    if not p.covers(q):
        raise ValueError(f"{p.name} does not cover the query")
    kinds = column_kinds(catalog, p)
    if plan in ("sortagg", "eager"):
        return _by_parent(catalog, q, p, plan, kinds)
    got = positions_of(catalog, q, p, collapsing, join)
    if got is None:
        return _empty(catalog, q, p, kinds)
    df, literal, _ = got
    for c, v in literal.items():
        if c in q.columns:
            df = df.withColumn(c, F.lit(v).cast(kinds[c]))
    return _finish(df, q, p, kinds)


def _finish(df: DataFrame, q: StarQuery, p: SortedProjection, kinds: dict[str, str]) -> DataFrame:
    if not q.aggs:
        return _ordered(layout.copies(df, q.columns), q)
    cols = needed_columns(p, q)
    if q.columns == (cols[-1],) == (p.sort_cols[0],) and all(a.fn == "count" for a in q.aggs):
        # values of the leading column are unique: a run is a group
        return _ordered(df.select(*q.columns, *[F.col("c").alias(a.alias) for a in q.aggs]), q)
    out = df.groupBy(*q.columns).agg(*[weighted(a, F.col(a.col) if a.col else None, F.col("c"), kinds.get(a.col, ""), F.col(a.by) if a.by else None) for a in q.aggs])
    return _ordered(out, q)


def _ordered(df: DataFrame, q: StarQuery) -> DataFrame:
    df = df.orderBy(*q.order) if q.order else df
    return df.limit(q.limit) if q.limit is not None else df


def _empty(catalog, q: StarQuery, p: SortedProjection, kinds: dict[str, str]) -> DataFrame:
    """No rows, of the same schema (and the one row of an ungrouped aggregate)."""
    tables = runs.build_runs(catalog, p)
    none = tables[p.sort_cols[0]].frame.where("false").select("f", "c", *[F.lit(None).cast(kinds[c]).alias(c) for c in q.needed])
    return _finish(none, q, p, kinds)


def _by_parent(catalog, q: StarQuery, p: SortedProjection, plan: str, kinds: dict[str, str]) -> DataFrame:
    """Innermost runs aggregated by parent run, then joined with the group column's runs and regrouped."""
    *_, group, inner = needed_columns(p, q)
    if q.columns != (group,) or p.depth(inner) != p.depth(group) + 1 or any(a.fn not in ("sum", "count") for a in q.aggs):
        raise ValueError("the query does not group by the column above its innermost one")
    tables = runs.build_runs(catalog, p)
    above = StarQuery(q.base, q.joins, tuple(x for x in q.preds if x.col != inner), (group,), ())
    got = positions_of(catalog, above, p)
    if got is None:
        return _empty(catalog, q, p, kinds)
    outer = got[0].select(F.col("f").alias("of"), group)
    # the inner runs lie in the span that the parents were found in
    values = _values(tables[inner], q, got[2], True)
    if plan == "eager":
        if any(x.col == group for x in q.preds):
            values = values.join(outer.select("of"), F.col("parent_f") == F.col("of"), "left_semi")
        sums = _partial(values.groupBy("parent_f"), q, inner, kinds)
        joined = outer.join(sums, F.col("of") == F.col("parent_f"))
    else:
        # a merge join on the group's key leaves rows in its order, so the aggregate streams
        hinted = outer.hint("merge").join(values.hint("merge"), F.col("of") == F.col("parent_f"))
        sums = _partial(hinted.groupBy("of"), q, inner, kinds).withColumnRenamed("of", "_of")
        joined = outer.join(sums, F.col("of") == F.col("_of"))
    out = []
    for a in q.aggs:
        total = F.sum(f"_{a.alias}")
        out.append((total.cast("double") if kinds.get(a.col) == "double" else total).alias(a.alias))
    return _ordered(joined.groupBy(group).agg(*out), q)


def _partial(grouped, q: StarQuery, inner: str, kinds: dict[str, str]) -> DataFrame:
    aggs = [F.sum(F.col("c") if a.fn == "count" else exact(F.col(inner), kinds[inner], inner) * F.col("c")).alias(f"_{a.alias}") for a in q.aggs]
    return grouped.agg(*aggs)


def last_children(catalog, q: StarQuery, p: SortedProjection) -> DataFrame:
    """MAX of the column right below the group column, read from each run's last child only (MIN: the first).

    In a nested sort a run's greatest value of the next column is the child
    that ends where the run ends, so an equality of ends replaces the band join.
    Where a comparison takes children away, or a first child is null (nulls sort
    first, and MIN passes over them), the general rewrite answers instead.
    """
    (agg,) = q.aggs
    cols = needed_columns(p, q)
    group, inner = cols[-2], cols[-1]
    if agg.fn not in ("max", "min") or agg.col != inner or q.columns != (group,) or p.depth(inner) != p.depth(group) + 1:
        raise ValueError("the query is not a MAX or MIN right below its group column")
    kinds = column_kinds(catalog, p)
    rt = runs.build_runs(catalog, p)[inner]
    nulls = agg.fn == "min" and catalog.made(("has nulls", rt.path), lambda: not rt.frame.where("v is null").isEmpty())
    if nulls or any(x.col == inner for x in q.preds):
        return rewrite_runs(catalog, q, p)
    above = StarQuery(q.base, q.joins, q.preds, (group,), ())
    got = positions_of(catalog, above, p)
    if got is None:
        return _empty(catalog, q, p, kinds)
    key = (lambda: F.col("f") + F.col("c")) if agg.fn == "max" else (lambda: F.col("f"))
    outer = got[0].select(key().alias("_k"), group)
    child = _values(rt, q, got[2], False).select(key().alias("_k"), inner)
    return _ordered(outer.join(child, "_k").groupBy(group).agg(getattr(F, agg.fn)(inner).alias(agg.alias)), q)
