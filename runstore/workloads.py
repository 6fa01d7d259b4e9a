"""Projections, queries and views of the experiments, over the given tables."""

from __future__ import annotations

import datetime as dt

from runstore.plans import views
from runstore.spec import Agg, Join, Pred, SortedProjection, StarQuery

ORDERS = Join("orders", "l_orderkey", "o_orderkey")
CUSTOMER = Join("customer", "o_custkey", "c_custkey")

S1 = SortedProjection("s1", "lineitem", (), ("l_shipdate", "l_suppkey"))
S2 = SortedProjection("s2", "lineitem", (ORDERS,), ("o_orderdate", "l_suppkey", "l_shipdate"))
S2B = SortedProjection("s2b", "lineitem", (ORDERS,), ("o_orderdate", "l_shipdate"))
S4 = SortedProjection("s4", "lineitem", (ORDERS, CUSTOMER), ("l_returnflag", "c_nationkey", "l_extendedprice"))
#: The literal shallow order: other columns only tie-break.
S4S = SortedProjection("s4s", "lineitem", (ORDERS, CUSTOMER), ("l_returnflag", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice", "l_suppkey", "l_quantity", "l_discount", "l_tax", "l_shipdate", "l_linestatus"), aligned=False, stored=("l_returnflag", "c_nationkey", "l_extendedprice"))
S5 = SortedProjection("s5", "lineitem", (), ("l_returnflag", "l_linestatus", "l_quantity", "l_suppkey"))
S6 = SortedProjection("s6", "events", (), ("event_type", "user_id", "day"), derived=(("day", "cast(cast(ts as date) as timestamp_ntz)"),))
S7 = SortedProjection("s7", "documents", (), ("lang", "source", "n_chars"))
S1Q = SortedProjection("s1q", "lineitem", (), ("l_shipdate", "l_suppkey", "l_quantity"))
S4W = SortedProjection("s4w", "lineitem", (ORDERS, CUSTOMER), ("l_returnflag", "l_linestatus", "c_nationkey", "c_mktsegment", "l_extendedprice"))

#: Days of the range sweep, and the day of the equality queries.
SWEEP = ("1995-09-04", "1996-09-11", "1998-05-24", "2000-02-13", "2001-02-24", "2001-10-10")
DAY = "1998-06-15"


def day(text: str) -> dt.datetime:
    return dt.datetime.fromisoformat(text)


_N = (Agg("count", None, "n_items"),)
_LAST = (Agg("max", "l_shipdate", "last_ship"),)


def q1(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (), (Pred("l_shipdate", ">", day(d)),), ("l_shipdate",), _N)


def q2(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (), (Pred("l_shipdate", "=", day(d)),), ("l_suppkey",), _N)


def q3(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (), (Pred("l_shipdate", ">", day(d)),), ("l_suppkey",), _N)


def q4(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (ORDERS,), (Pred("o_orderdate", ">", day(d)),), ("o_orderdate",), _LAST)


def q5(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (ORDERS,), (Pred("o_orderdate", "=", day(d)),), ("l_suppkey",), _LAST)


def q6(d: str = DAY) -> StarQuery:
    return StarQuery("lineitem", (ORDERS,), (Pred("o_orderdate", ">", day(d)),), ("l_suppkey",), _LAST)


def q7(flag: str = "R") -> StarQuery:
    return StarQuery("lineitem", (ORDERS, CUSTOMER), (Pred("l_returnflag", "=", flag),), ("c_nationkey",), (Agg("sum", "l_extendedprice", "lost_revenue"),))


#: Each query with the projection that answers it.
QUERIES = {"q1": (q1(), S1), "q2": (q2(), S1), "q3": (q3(), S1), "q4": (q4(), S2), "q5": (q5(), S2), "q6": (q6(), S2), "q7": (q7(), S4)}

_W7 = q7()
#: Changes of the queries that views may or may not serve.
ADHOC = {
    "a": q7("A"),
    "b": StarQuery("lineitem", _W7.joins, (*_W7.preds, Pred("l_linestatus", "=", "O")), _W7.columns, _W7.aggs),
    "c": StarQuery("lineitem", _W7.joins, _W7.preds, _W7.columns, (Agg("avg", "l_extendedprice", "mean_price"),)),
    "d": StarQuery("lineitem", _W7.joins, _W7.preds, ("c_mktsegment",), _W7.aggs),
    "e": StarQuery("lineitem", (), (*q3().preds, Pred("l_quantity", ">", 25.0)), ("l_suppkey",), _N),
    "f": StarQuery("lineitem", (), (*q3().preds, Pred("l_suppkey", "in", (3, 5, 7))), ("l_suppkey",), _N),
}

DEEP = (Pred("l_quantity", "=", 10.0), Pred("l_suppkey", "=", 7))
DEEP_COLS = ("l_returnflag", "l_linestatus", "l_quantity", "l_suppkey")


def view_definitions():
    """Views of the seven queries: generalized, then merged into five."""
    return views.merge_definitions([views.generalize(q, f"v{n[1:]}") for n, (q, _) in QUERIES.items()])


def view(name: str):
    return next(v for v in view_definitions() if v.name == name)


PROJECTIONS = [S1, S1Q, S2, S2B, S4, S4W, S5]
