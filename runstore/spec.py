"""What the planner's stages pass on: projections, queries, views, plans (driver-side values only)."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Columns of money, rates and quantities that hold at most two decimals: their sums are exact in this type.
MONEY = "decimal(18,2)"
MONEY_COLUMNS = frozenset({"l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "s_acctbal", "p_retailprice", "value"})

OPS = ("=", "<>", "<", "<=", ">", ">=", "between", "in", "like", "null", "not null")


@dataclass(frozen=True)
class Join:
    """An inner key join: left_key of what is joined so far equals right_key of table."""

    table: str
    left_key: str
    right_key: str


@dataclass(frozen=True)
class Pred:
    """One comparison of a column with constants; conjunctions are tuples of these."""

    col: str
    op: str
    value: Any = None

    def __post_init__(self) -> None:
        if self.op not in OPS:
            raise ValueError(f"unknown comparison {self.op}")

    def on(self, c: Column) -> Column:
        v = self.value
        match self.op:
            case "=":
                return c == F.lit(v)
            case "<>":
                return c != F.lit(v)
            case "<":
                return c < F.lit(v)
            case "<=":
                return c <= F.lit(v)
            case ">":
                return c > F.lit(v)
            case ">=":
                return c >= F.lit(v)
            case "between":
                return c.between(F.lit(v[0]), F.lit(v[1]))
            case "in":
                return c.isin(*v)
            case "like":
                return c.like(v)
            case "null":
                return c.isNull()
        return c.isNotNull()

    @property
    def contiguous(self) -> bool:
        """Whether the values that pass lie next to each other in a sorted column."""
        return self.op in ("=", "<", "<=", ">", ">=", "between", "null", "not null")


@dataclass(frozen=True)
class Agg:
    """count (col None: of rows), sum, min, max, avg, count_distinct, approx_distinct, var and stddev (population) of a column.

    min_by and max_by give `col` where `by` is least or greatest (of several, the least or the greatest value).
    """

    fn: str
    col: str | None
    alias: str
    by: str | None = None


@dataclass(frozen=True)
class StarQuery:
    """One block: key joins, a conjunction of comparisons, output or group columns, aggregates.

    Without aggregates it is a plain projection with bag semantics.
    """

    base: str
    joins: tuple[Join, ...] = ()
    preds: tuple[Pred, ...] = ()
    columns: tuple[str, ...] = ()
    aggs: tuple[Agg, ...] = ()
    order: tuple[str, ...] = ()
    limit: int | None = None

    @property
    def needed(self) -> set[str]:
        return {p.col for p in self.preds} | set(self.columns) | {c for a in self.aggs for c in (a.col, a.by) if c}


@dataclass(frozen=True)
class SortedProjection:
    """An expression (base with its key joins) and a global sort order of its columns.

    aligned: every stored column is a sort column, so runs nest.  Otherwise
    `stored` columns are run-length encoded in that order without being part of it.
    derived: columns computed from others, as SQL text.
    delta: starts are written delta-coded.
    """

    name: str
    base: str
    joins: tuple[Join, ...]
    sort_cols: tuple[str, ...]
    aligned: bool = True
    stored: tuple[str, ...] = ()
    derived: tuple[tuple[str, str], ...] = ()
    delta: bool = False

    def frame(self, catalog) -> DataFrame:
        return joined(catalog, self.base, self.joins, dict(self.derived))

    def depth(self, col: str) -> int:
        return self.sort_cols.index(col) + 1

    def covers(self, q: StarQuery) -> bool:
        return self.aligned and self.base == q.base and set(self.joins) == set(q.joins) and q.needed <= set(self.sort_cols)


@dataclass
class RunTable:
    """Runs of one column: rows (f, v, c[, parent_f]), ordered by f on disk, and again by v."""

    projection: str
    column: str
    depth: int
    layout: str
    path: str
    by_value: str
    rows: int
    runs: int
    frame: DataFrame = field(repr=False)
    manifest: str = ""


@dataclass(frozen=True)
class Span:
    """Positions lo..hi, both included."""

    lo: int
    hi: int


@dataclass(frozen=True)
class ViewDefinition:
    """A grouped aggregate without the parameters of the queries it serves."""

    name: str
    base: str
    joins: tuple[Join, ...]
    groups: tuple[str, ...]
    aggs: tuple[Agg, ...]


@dataclass
class StrategyPlan:
    """What the router decided, and why other ways were not taken."""

    strategy: str
    source: str = ""
    fallback_reason: str = ""
    selectivity: float | None = None
    estimates: dict[str, float] = field(default_factory=dict)


def joined(catalog, base: str, joins: tuple[Join, ...], derived: dict[str, str] | None = None) -> DataFrame:
    """The base table with its key joins; Catalyst picks the physical joins."""

    def add(df: DataFrame, j: Join) -> DataFrame:
        right = catalog.table(j.table)
        return df.join(right, df[j.left_key] == right[j.right_key])

    df = reduce(add, joins, catalog.table(base))
    return df.withColumns({c: F.expr(e) for c, e in derived.items()}) if derived else df
