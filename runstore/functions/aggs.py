"""Aggregates over runs: values weighted by counts, exact for money."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from runstore.spec import MONEY, MONEY_COLUMNS, Agg


def is_money(col: str | None, kind: str) -> bool:
    return kind == "double" and col in MONEY_COLUMNS


def exact(c: Column, kind: str, col: str | None) -> Column:
    """Doubles that are declared to have two decimals as decimals, so that sums do not depend on order; others stay doubles."""
    return c.cast(MONEY) if is_money(col, kind) else c


def weighted(agg: Agg, v: Column | None, c: Column, kind: str = "", by: Column | None = None) -> Column:
    """An aggregate of rows, from runs with value v and count c."""
    out = _weighted(agg.fn, None if v is None else exact(v, kind, agg.col), v, c, kind, by)
    return out.alias(agg.alias)


def _moments(n: Column, s: Column, q: Column) -> Column:
    """Population variance of n values with sum s and sum of squares q, never below zero."""
    return F.greatest(q / n - (s / n) * (s / n), F.lit(0.0))


def _weighted(fn: str, x: Column | None, v: Column | None, c: Column, kind: str, by: Column | None) -> Column:
    if fn == "count":
        return F.coalesce(F.sum(c if v is None else F.when(v.isNotNull(), c).otherwise(F.lit(0))), F.lit(0).cast("long"))
    held = F.when(v.isNotNull(), c)
    match fn:
        case "sum":
            total = F.sum(x * c)
            return total.cast("double") if kind == "double" else total
        case "avg":
            return F.sum(x * c).cast("double") / F.sum(held)
        case "var" | "stddev":
            out = _moments(F.sum(held), F.sum(x * c).cast("double"), F.sum(x * x * c).cast("double"))
            return F.sqrt(out) if fn == "stddev" else out
    return _unweighted(fn, v, by)


def _unweighted(fn: str, v: Column, by: Column | None) -> Column:
    """Aggregates that do not ask how often a value occurs."""
    match fn:
        case "min":
            return F.min(v)
        case "max":
            return F.max(v)
        case "count_distinct":
            return F.count_distinct(v)
        case "approx_distinct":
            return F.approx_count_distinct(v, 0.02)
        case "min_by":
            return F.min(F.when(by.isNotNull(), F.struct(by.alias("k"), v.alias("v"))))["v"]
        case "max_by":
            return F.max(F.when(by.isNotNull(), F.struct(by.alias("k"), v.alias("v"))))["v"]
    raise ValueError(f"unknown aggregate {fn}")


def plain(agg: Agg, kind: str = "") -> Column:
    """The same aggregate of rows."""
    v = F.col(agg.col) if agg.col else None
    x = None if v is None else exact(v, kind, agg.col)
    match agg.fn:
        case "count":
            out = F.count("*") if v is None else F.count(v)
        case "sum":
            out = F.sum(x).cast("double") if kind == "double" else F.sum(x)
        case "avg":
            out = F.sum(x).cast("double") / F.count(v)
        case "var" | "stddev":
            out = _moments(F.count(v), F.sum(x).cast("double"), F.sum(x * x).cast("double"))
            out = F.sqrt(out) if agg.fn == "stddev" else out
        case _:
            out = _unweighted(agg.fn, v, F.col(agg.by) if agg.by else None)
    return out.alias(agg.alias)
