import datetime as dt
import json
import random

import duckdb
import pytest

from runstore import queries
from runstore import workloads as w
from runstore.catalog import Catalog, catalog
from runstore.operators import bandjoin, concat, deep, positions, runs
from runstore.plans import baselines, collapse, rewrite, router, sqltext, views
from runstore.sources import datasource, layout
from runstore.spec import Agg, Pred, SortedProjection, Span, StarQuery

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents".split():
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


@pytest.fixture(scope="module")
def cat(spark):
    return catalog(spark, SF)


def rows(result) -> list:
    return sorted((tuple(r) for r in result), key=str)


def tiling(rnd, n, longest):
    out, at = [], 1
    while at <= n:
        c = min(rnd.randint(1, longest), n + 1 - at)
        out.append((at, rnd.choice("abc"), c))
        at += c
    return out


def nested(rnd, outer, longest):
    out = []
    for f, _, c in outer:
        at = f
        while at < f + c:
            k = min(rnd.randint(1, longest), f + c - at)
            out.append((at, rnd.randint(1, 9), k, f))
            at += k
    return out


# ---- worked example and invariants -----------------------------------------------------------


FIG3 = [(1, 1, 1), (1, 1, 4), (1, 2, 4), (1, 2, 5), (1, 2, 5), (2, 1, 1), (2, 1, 1), (2, 3, 1), (2, 3, 2), (2, 3, 2), (2, 3, 3), (2, 3, 4)]


def test_worked_example(spark):
    got = {}
    example = OneTable(spark, spark.createDataFrame(FIG3, "a int, b int, x int"))
    for r in queries.all_runs(example, SortedProjection("fig3", "t", (), ("a", "b", "x"))).collect():
        got.setdefault(r["column"], []).append((r["f"], r["v"], r["c"]))
    assert sorted(got["a"]) == [(1, 1, 5), (6, 2, 7)]
    assert sorted(got["b"]) == [(1, 1, 2), (3, 2, 3), (6, 1, 2), (8, 3, 5)]
    assert len(got["x"]) == 9 and sum(c for _, _, c in got["x"]) == 12
    assert layout.choose(12, 9, "int", 0) == "points" and layout.choose(12, 4, "int", 0) == "runs"
    line = spark.createDataFrame([(i + 1, r[2]) for i, r in enumerate(FIG3)], "pos long, v int")
    for block in (1, 5, 64):
        assert runs.unbroken_runs(line, block).count() == 7


@pytest.mark.parametrize("p", [w.S1, w.S2, w.S4, w.S5, w.S6, w.S7], ids=lambda p: p.name)
def test_invariants(cat, p):
    t = runs.build_runs(cat, p)
    n = p.frame(cat).count()
    cols = [t[c].frame for c in p.sort_cols]
    for x in cols:
        assert x.agg({"c": "sum"}).first()[0] == n and runs.check_tiling(x).count() == 0
    for a, b in zip(cols, cols[1:]):
        assert runs.check_nesting(a, b).count() == 0
    lead = cols[0]
    assert lead.select("v").distinct().count() == lead.count()


def test_runs_of_all_columns_come_from_a_given_table(spark, con):
    df = queries.QUERIES["fig3_runs"](spark, SF)
    want = rows(con.execute(queries.ORACLES["fig3_runs"]).fetchall())
    assert rows(df.select("column", "f", "v", "c").collect()) == want
    total = con.execute("select count(*) from lineitem").fetchone()[0]
    assert all(sum(r[3] for r in want if r[0] == c) == total for c in queries.FIG3_PROJECTION.sort_cols)


def test_reconstruct(cat):
    p = w.S5
    got = runs.reconstruct(cat, p).select(*p.sort_cols)
    assert rows(got.collect()) == rows(cat.table("lineitem").select(*p.sort_cols).collect())


def test_reconstruct_joins_runs_and_not_rows(spark):
    """One run of many rows is a small file: its rows must not be taken for a side that fits a broadcast."""
    df = spark.range(200_000).selectExpr("'a' as a", "id % 2 as b", "id as d")
    c, p = OneTable(spark, df), SortedProjection("long", "t", (), ("a", "b", "d"))
    got = runs.reconstruct(c, p)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" in plan and plan.rindex("Generate explode") < plan.index("Join"), plan
    assert got.count() == got.select("pos").distinct().count() == 200_000
    assert got.select(*p.sort_cols).exceptAll(df).isEmpty()


class OneTable(Catalog):
    def __init__(self, spark, df):
        super().__init__(spark, "none")
        self.df = df

    def table(self, name):
        return self.df


def test_nulls_and_odd_values(spark):
    data = [(None, None, 1.0), (None, "x", float("nan")), ("", None, -0.0), ("", "", 0.0), ("b", "y", -5.5), ("b", "y", None)]
    df = spark.createDataFrame(data, "a string, b string, d double")
    c, p = OneTable(spark, df), SortedProjection("odd", "t", (), ("a", "b", "d"))
    t = runs.build_runs(c, p)
    assert [(r["f"], r["v"], r["c"]) for r in t["a"].frame.orderBy("f").collect()] == [(1, None, 2), (3, "", 2), (5, "b", 2)]
    q = StarQuery("t", (), (Pred("b", "<>", "x"),), ("a",), (Agg("count", "d", "n"), Agg("count", None, "m")))
    assert rows(rewrite.rewrite_runs(c, q, p).collect()) == rows(baselines.run_columnar(c, q).collect())
    q = StarQuery("t", (), (Pred("a", "null"),), ("b",), (Agg("count", None, "m"),))
    assert rows(rewrite.rewrite_runs(c, q, p).collect()) == rows(baselines.run_columnar(c, q).collect())


@pytest.mark.parametrize("data", [[], [("a", 1)], [("a", 1)] * 5, [(str(i), i) for i in range(9)]])
def test_edge_tables(spark, data):
    c, p = OneTable(spark, spark.createDataFrame(data, "a string, b int")), SortedProjection("edge", "t", (), ("a", "b"))
    q = StarQuery("t", (), (), ("a",), (Agg("max", "b", "m"), Agg("count", None, "n")))
    assert rows(rewrite.rewrite_runs(c, q, p).collect()) == rows(baselines.run_columnar(c, q).collect())
    assert runs.reconstruct(c, p).count() == len(data)


def test_positions_do_not_depend_on_partitions(spark, cat):
    order = ["l_shipdate", "l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice"]
    df = cat.table("lineitem").select(*order)
    seen = []
    for n in (1, 4, 13):
        spark.conf.set("spark.sql.shuffle.partitions", str(n))
        got = positions.assign_positions(cat, df, order).select("pos", "l_orderkey", "l_linenumber").collect()
        assert sorted(r["pos"] for r in got) == list(range(1, 6001))
        seen.append(rows(got))
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert seen[0] == seen[1] == seen[2]


# ---- joins -----------------------------------------------------------------------------------


@pytest.mark.parametrize("block", [1, 7, 64, 4096])
def test_containment_joins_agree(spark, block):
    rnd = random.Random(block)
    outer = tiling(rnd, 300, 40)
    inner = nested(rnd, outer, 9)
    some = [r for r in outer if r[1] != "a"]
    want = sorted((i[0], i[1], i[2], o[1]) for o in some for i in inner if o[0] <= i[0] <= o[0] + o[2] - 1)
    o = spark.createDataFrame(some, "f long, ov string, c long")
    i = spark.createDataFrame(inner, "f long, iv int, n long, parent_f long").select("f", "iv", "n", "parent_f")
    for how in bandjoin.STRATEGIES:
        got = bandjoin.containment_join(o, i, how, block).select("f", "iv", "n", "ov").collect()
        assert sorted(tuple(r) for r in got) == want, how


def test_strict_upper_bound_loses_rows(cat):
    """The inclusive bound is right: a strict one drops each outer run's last position."""
    t = runs.build_runs(cat, w.S4)
    o = t["c_nationkey"].frame.selectExpr("f as a", "c as n")
    i = t["l_extendedprice"].frame
    assert i.join(o, (i.f >= o.a) & (i.f < o.a + o.n - 1)).agg({"c": "sum"}).first()[0] < 6000
    assert i.join(o, (i.f >= o.a) & (i.f <= o.a + o.n - 1)).agg({"c": "sum"}).first()[0] == 6000


@pytest.mark.parametrize("block", [1, 7, 64, 4096])
def test_overlap_and_concatenation_agree(spark, block):
    rnd = random.Random(block)
    a, b = tiling(rnd, 200, 30), tiling(rnd, 200, 11)
    da, db = (spark.createDataFrame(x, "f long, v string, c long") for x in (a, b))
    want = sorted((max(x[0], y[0]), min(x[0] + x[2], y[0] + y[2]) - max(x[0], y[0]), x[1], y[1]) for x in a for y in b if max(x[0], y[0]) < min(x[0] + x[2], y[0] + y[2]))
    pairs = bandjoin.overlap_join(da.withColumnRenamed("v", "x"), db.withColumnRenamed("v", "y"), block)
    assert sorted(tuple(r) for r in pairs.select("f", "c", "x", "y").collect()) == want

    def cells(segments):
        return sorted((p, r["x"], r["y"]) for r in segments for p in range(r["f"], r["f"] + r["c"]))

    rows_of = cells([dict(f=f, c=c, x=x, y=y) for f, c, x, y in want])
    assert cells(concat.concat_runs({"x": da, "y": db}, block).collect()) == rows_of
    if block > 1:
        assert cells(concat.concat_by_function(da, db, ("x", "y"), block).collect()) == rows_of


# ---- rewriting -------------------------------------------------------------------------------

DAYS = [*w.SWEEP, "1995-04-05", "1990-01-01", "2005-01-01"]


@pytest.mark.parametrize("name", ["q1", "q2", "q3", "q4", "q5", "q6"])
def test_rewriting_for_all_days(cat, con, name):
    make = getattr(w, name)
    p = w.QUERIES[name][1]
    for d in DAYS:
        want = rows(con.execute(queries.SQL[name].replace(queries.D, f"TIMESTAMP '{d} 00:00:00'")).fetchall())
        for collapsing in (True, False):
            assert rows(rewrite.rewrite_runs(cat, make(d), p, collapsing).collect()) == want, (d, collapsing)
        v = next(v for v in w.view_definitions() if not views.match_view(make(d), v))
        assert rows(views.answer_from_view(cat, make(d), v).collect()) == want


@pytest.mark.parametrize("key", [k for k in queries.ORACLES if k.split("_")[0] in ("q7", "adhoc", "deep", "shallow", "stream", "hybrid", "sqltext", "io", "set")])
def test_queries_against_sql(spark, con, key):
    df = queries.QUERIES[key](spark, SF)
    c = con.execute(queries.ORACLES[key])
    names = [x[0] for x in c.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.select(*names).collect()) == rows(c.fetchall())


def test_span_collapse_prunes(cat):
    t = runs.build_runs(cat, w.S1)
    span = collapse.collapse_span(cat, t["l_shipdate"], w.q3().preds)
    plan = layout.read_runs(t["l_suppkey"], span)._jdf.queryExecution().executedPlan().toString()
    assert f"GreaterThanOrEqual(f,{span.lo})" in plan and f"LessThanOrEqual(f,{span.hi})" in plan
    assert collapse.is_contiguous(w.S1, w.q3(), "l_shipdate") and not collapse.is_contiguous(w.S2, w.q4(), "o_orderdate")
    assert not collapse.is_contiguous(w.S5, StarQuery("lineitem", (), w.DEEP, w.DEEP_COLS), "l_suppkey")


def test_no_nested_loops(cat):
    for name, (q, p) in w.QUERIES.items():
        plan = rewrite.rewrite_runs(cat, q, p)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan, name


def test_collapse_spans(spark):
    df = spark.createDataFrame([(1, 2), (3, 4), (9, 1), (10, 5), (20, 1)], "f long, c long")
    assert collapse.collapse_spans(df) == [Span(1, 6), Span(9, 14), Span(20, 20)]
    assert collapse.collapse_spans(df, 2) is None


# ---- views, router, text ---------------------------------------------------------------------


def test_views_match_parameters_only():
    v = w.view("v7")
    assert not views.match_view(w.ADHOC["a"], v) and not views.match_view(w.ADHOC["f"], w.view("v23"))
    assert {n for n in "bcde" if all(views.match_view(w.ADHOC[n], x) for x in w.view_definitions())} == set("bcde")
    assert sorted(x.name for x in w.view_definitions()) == ["v1", "v23", "v4", "v56", "v7"]


def test_refresh_equals_rebuild(spark, cat):
    v = w.view("v56")
    base = spark.createDataFrame([(1, dt.datetime(2000, 1, d), s, dt.datetime(2001, 1, x)) for d, s, x in [(1, 1, 3), (1, 1, 9), (1, 2, 4), (2, 1, 5)]], "k int, o_orderdate timestamp_ntz, l_suppkey long, l_shipdate timestamp_ntz")
    old = views.delta_of(v, base)
    gone = base.where("day(l_shipdate) in (9, 5)")
    left = base.where("day(l_shipdate) not in (9, 5)")
    got = views.refresh(v, old, None, gone, left)
    assert rows(got.select(*v.groups, "last_ship").collect()) == rows(views.delta_of(v, left).collect())


def test_router(cat):
    e = queries.engine(cat)
    assert e.plan(w.q7()).strategy == "views"
    assert [e.plan(w.ADHOC[k]).strategy for k in "abcdef"] == ["views", "runs", "runs", "runs", "runs", "views"]
    far = StarQuery("lineitem", (), (), ("l_tax",), (Agg("count", None, "n"),))
    assert e.plan(far).strategy == "columnar" and "no projection" in e.plan(far).fallback_reason
    for s in ("row", "columnar", "vertical", "index", "runs", "runs_nocollapse"):
        assert rows(e.query(w.q7(), s).collect()) == rows(e.query(w.q7()).collect())


def test_sql_text():
    q = sqltext.parse("SELECT l_suppkey, COUNT(*) AS n FROM lineitem WHERE l_shipdate BETWEEN '1998-01-01' AND '1998-02-01' AND l_suppkey IN (1, 2) GROUP BY l_suppkey ORDER BY l_suppkey LIMIT 3")
    assert q.preds[0].op == "between" and q.preds[1].value == (1, 2) and q.limit == 3 and q.order == ("l_suppkey",)
    two = sqltext.parse("select max(l_shipdate) as m from orders join lineitem on o_orderkey = l_orderkey where o_orderstatus like 'F%'")
    assert two.base == "lineitem" and two.joins == (w.ORDERS,)
    for text in ("select 1", "select l_suppkey from lineitem where l_suppkey = 1 or l_suppkey = 2", "select l_suppkey from lineitem, orders", "drop table x", "select nope from lineitem", "select l_suppkey, count(*) from lineitem"):
        assert sqltext.parse(text) is None


def test_manifest(cat, spark):
    path = cat.save_manifest("m", [{"a": 1}, {"a": 2}])
    assert sorted(json.loads(r[0])["a"] for r in spark.read.text(path).collect()) == [1, 2]


def test_scan_metrics(cat):
    got = {(r["query"], r["strategy"]): r for r in queries.scan_counts(cat).collect()}
    assert got["q1", "columnar"]["rows_read"] == 6000
    assert 0 < got["q1", "runs"]["rows_read"] < 6000 and got["q7", "views"]["rows_read"] == 75
    assert got["q1", "runs"]["bytes_read"] < got["q1", "columnar"]["bytes_read"]


def test_outer_rows(cat):
    got = {r["query"]: (r["seek"], r["collapsed"]) for r in queries.outer_rows(cat).collect()}
    assert got["q3"][0] > 100 and got["q3"][1] == 1


# ---- limits and fallbacks --------------------------------------------------------------------


def test_limits_shuffle_instead_of_broadcasting(spark, cat, monkeypatch):
    """With limits of a handful of rows every strategy gives the same rows, and holds no side in every task."""
    outer = runs.build_runs(cat, w.S1)["l_shipdate"].frame.select("f", "c", "v").withColumnRenamed("v", "d")
    inner = runs.build_runs(cat, w.S1)["l_suppkey"].frame.select("f", "v", "parent_f")
    want = rows(bandjoin.containment_join(outer, inner, "parent").collect())
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    monkeypatch.setattr(bandjoin, "BROADCAST_RUNS", 5)
    try:
        for how in ("nl", "crossrow", "probe", "broadcast_block"):
            df = bandjoin.containment_join(outer, inner, how)
            plan = df._jdf.queryExecution().executedPlan().toString()
            assert "Broadcast" not in plan and "MapInArrow" not in plan, how
            assert rows(df.collect()) == want, how
        monkeypatch.setattr(bandjoin, "BROADCAST_RUNS", 2)  # the leading column has three runs
        got = deep.intersect_seeks(cat, w.S5, w.DEEP, w.DEEP_COLS)
        assert "Broadcast" not in got._jdf.queryExecution().executedPlan().toString()
        assert rows(got.collect()) == rows(cat.table("lineitem").where("l_quantity = 10 and l_suppkey = 7").select(*w.DEEP_COLS).collect())
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_no_window_over_all_rows(spark):
    line = spark.createDataFrame([(i + 1, i // 90) for i in range(1000)], "pos long, v int")
    df = runs.unbroken_runs(line, 64)
    assert rows(df.select("f", "v", "c").collect()) == rows((90 * k + 1, k, min(90, 1000 - 90 * k)) for k in range(12))
    assert "SinglePartition" not in df._jdf.queryExecution().executedPlan().toString()


def test_long_runs_are_cut_before_they_are_expanded(spark, monkeypatch):
    df = spark.createDataFrame([(1, 200000, "a"), (200001, 3, "b")], "f long, c long, v string")
    assert layout.pieces(df).agg({"c": "max"}).first()[0] == layout.PIECE and layout.pieces(df).agg({"c": "sum"}).first()[0] == 200003
    got = layout.positions_of_runs(df)
    assert got.count() == 200003 and got.agg({"pos": "max"}).first()[0] == 200003
    huge = spark.createDataFrame([(1, 3_000_000_000, "a")], "f long, c long, v string")
    assert layout.pieces(huge).count() == -(-3_000_000_000 // layout.PIECE)
    assert bandjoin.touched(huge.select("f", "c"), 1 << 30) == 3


def test_unknown_strategies_and_paths(spark, cat):
    e = queries.engine(cat)
    with pytest.raises(ValueError):
        e.query(w.q7(), "fastest")
    with pytest.raises(ValueError):
        e.query(StarQuery("lineitem", (), (), ("l_tax",), (Agg("count", None, "n"),)), "hybrid")
    datasource.register(spark)
    with pytest.raises(Exception):
        spark.read.format("runstore").option("path", "/nowhere/at/all").option("v", "long").load().count()


def test_router_takes_the_hybrid_where_nothing_covers(cat, con):
    e = queries.engine(cat)
    assert e.plan(queries._HYBRID).strategy in ("hybrid", "columnar") and "hybrid" in e.plan(queries._HYBRID).estimates
    assert rows(e.query(queries._HYBRID, "hybrid").collect()) == rows(e.query(queries._HYBRID, "columnar").collect())


def test_seek_reads_a_span(cat):
    df = rewrite.rewrite_runs(cat, w.q7(), w.S4, collapsing=False, join="seek")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("GreaterThanOrEqual(f,") >= 2


def test_several_spans(cat, con):
    q = StarQuery("lineitem", (), (Pred("l_shipdate", "in", tuple(w.day(d) for d in ("1995-04-05", "1998-06-15", "1999-03-03"))),), ("l_suppkey",), (Agg("count", None, "n"),))
    df = rewrite.rewrite_runs(cat, q, w.S1)
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()
    assert rows(df.collect()) == rows(baselines.run_columnar(cat, q).collect())


def test_min_passes_over_null_children(spark):
    df = spark.createDataFrame([("a", None), ("a", 3), ("a", 5), ("b", None), ("c", 2)], "k string, x int")
    c, p = OneTable(spark, df), SortedProjection("nulls", "t", (), ("k", "x"))
    for fn in ("min", "max"):
        q = StarQuery("t", (), (), ("k",), (Agg(fn, "x", "m"),))
        assert rows(rewrite.last_children(c, q, p).collect()) == rows(baselines.run_columnar(c, q).collect())


def test_bucketed_sides_join_without_a_shuffle(spark, cat):
    outer = runs.build_runs(cat, w.S1)["l_shipdate"].frame.select("f", "c", "v").withColumnRenamed("v", "d")
    inner = runs.build_runs(cat, w.S1)["l_suppkey"].frame.select("f", "v")
    df, _, _ = bandjoin.bucketed_join(cat, outer, inner)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    assert rows(df.collect()) == rows(bandjoin.containment_join(outer, inner, "copartition").collect())


@pytest.mark.parametrize("key", ["adhoc_limit_views", "adhoc_empty_views", "adhoc_empty_runs", "q4_tail_pred", "q6_tail_pred", "sum_many_decimals", "view_follows_data", "runs_follow_data", "view_max_follows_data", "view_as_runs_q7", "outer_rows", "agg_stddev", "agg_arg", "agg_quantile", "io_partitioned", "stored_s2_l_shipdate"])
def test_more_queries_against_sql(spark, con, key):
    df = queries.QUERIES[key](spark, SF)
    c = con.execute(queries.ORACLES[key])
    names = [x[0] for x in c.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.select(*names).collect()) == rows(c.fetchall())
