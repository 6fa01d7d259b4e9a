"""Times the headline queries and prints one JSON line.

Run tables, views and baselines are built first (their seconds are reported
apart); every query then runs once to warm up and `REPEATS` times into a sink
that keeps nothing, and its median counts.
"""

from __future__ import annotations

import json
import os
import sys
import time
from statistics import geometric_mean, mean, median

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "3"))
STRATEGIES = ("row", "columnar", "views", "runs", "runs_nocollapse")
#: The claim that vertical partitions and indexes lose to rows is tested on all seven queries.
OTHERS = tuple(f"q{n}_{s}" for n in range(1, 8) for s in ("vertical", "index"))


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def seconds(fn) -> float:
    began = time.perf_counter()
    fn()
    return time.perf_counter() - began


def agg_share(c, times: dict[str, float]) -> float:
    """Share of Q2's time on a view that its regrouping takes (C6): with it less without it."""
    from runstore import workloads as w
    from runstore.plans import baselines, views

    run = lambda again: median(seconds(lambda: baselines.drain(views.answer_from_view(c, w.q2(), w.view("v23"), reaggregate=again))) for _ in range(REPEATS + 2))
    plain, regrouped = run(False), run(True)
    return max(0.0, regrouped - plain) / regrouped


def sweep(c, w) -> dict[str, dict[str, float]]:
    """Averages over all days of the sweep, of time and of its ratio to the floor (Q1, Q3, Q4, Q6)."""
    from runstore.plans import baselines, rewrite, views

    out = {}
    for n in ("q1", "q3", "q4", "q6"):
        p, make = w.QUERIES[n][1], getattr(w, n)
        sums = {"columnar": 0.0, "views": 0.0, "runs": 0.0, "floor": 0.0}
        for d in w.SWEEP:
            q = make(d)
            v = next(v for v in w.view_definitions() if not views.match_view(q, v))
            baselines.floor_time(c, q, p)
            sums["floor"] += baselines.floor_time(c, q, p)
            sums["columnar"] += seconds(lambda: baselines.drain(baselines.run_columnar(c, q)))
            sums["views"] += seconds(lambda: baselines.drain(views.answer_from_view(c, q, v)))
            sums["runs"] += seconds(lambda: baselines.drain(rewrite.rewrite_runs(c, q, p)))
        out[n] = {k: round(x / len(w.SWEEP), 4) for k, x in sums.items()} | {f"{k}_to_floor": round(sums[k] / sums["floor"], 2) for k in ("columnar", "views", "runs")}
    return out


def maintenance(c, w) -> dict[str, float]:
    """Seconds to bring a stored view up to date after inserts, and to build it anew."""
    from runstore.catalog import Catalog
    from runstore.plans import views

    own = Catalog(c.spark, c.sf_dir)
    v, rows = w.view("v23"), own.table("lineitem")
    built = seconds(lambda: views.build_view(own, v))
    few = own.stored(rows.where("l_orderkey % 100 = 7"), "few")
    old = views.build_view(own, v)
    return {"build": round(built, 2), "refresh_one_percent": round(seconds(lambda: own.stored(views.refresh(v, old, few), "fresh")), 2)}


def main() -> None:
    from runstore import queries
    from runstore import workloads as w
    from runstore.catalog import catalog
    from runstore.operators import runs
    from runstore.plans import baselines, views

    spark = session()
    c = catalog(spark, SF_DIR)
    build = {p.name: seconds(lambda p=p: runs.build_runs(c, p)) for p in (w.S1, w.S2, w.S2B, w.S4)}
    build |= {v.name: seconds(lambda v=v: views.build_view(c, v)) for v in w.view_definitions()}
    build |= {f"rows_{t}": seconds(lambda t=t: baselines.to_row_layout(c, t)) for t in ("lineitem", "orders", "customer")}
    times: dict[str, float] = {}
    names = [n for n in (f"{q}_{s}" for q in w.QUERIES for s in STRATEGIES) if n in queries.QUERIES]
    for name in (*names, *OTHERS, "q4_runs_s2b", "q4_runs_tail", "q6_runs_tail", "q7_runs_eager", "q7_runs_sortagg"):
        run = lambda name=name: baselines.drain(queries.QUERIES[name](spark, SF_DIR))
        run()
        times[name] = median(seconds(run) for _ in range(REPEATS))
    floor = {}
    for n, (q, p) in w.QUERIES.items():
        baselines.floor_time(c, q, p)
        floor[n] = median(baselines.floor_time(c, q, p) for _ in range(REPEATS))
    swept = sweep(c, w)
    choice = {n: queries.engine(c).plan(q).strategy for n, (q, _) in w.QUERIES.items()}
    best = {n: min(("columnar", "views", "runs"), key=lambda s, n=n: times[f"{n}_{s}"]) for n in w.QUERIES}
    ratio = lambda a, b: {n: round(a(n) / b(n), 2) for n in w.QUERIES}
    of = lambda s: lambda n: times[f"{n}_{s}"]
    slow = ratio(of("runs"), floor.get)
    out = {
        "metric": "seconds of Q1-Q7 from run tables",
        "value": round(sum(times[f"{n}_runs"] for n in w.QUERIES), 3),
        "unit": "sec",
        "queries": {k: round(v, 4) for k, v in times.items()},
        "sf": SF_DIR.rsplit("sf", 1)[-1],
        "floor": {k: round(v, 4) for k, v in floor.items()},
        "row_to_floor": ratio(of("row"), floor.get),
        "row_to_runs": ratio(of("row"), of("runs")),
        "row_to_views": ratio(of("row"), of("views")),
        "views_to_floor": ratio(of("views"), floor.get),
        "runs_to_floor": slow,
        "runs_to_floor_mean": [round(mean(slow.values()), 2), round(geometric_mean(slow.values()), 2)],
        "q2_view_aggregation_share": round(agg_share(c, times), 2),
        "sweep": swept,
        "vertical_to_row": ratio(of("vertical"), lambda n: times[f"{n}_row"]),
        "index_to_row": ratio(of("index"), lambda n: times[f"{n}_row"]),
        "router": {n: [choice[n], best[n], round(times[f"{n}_{choice[n]}"] / times[f"{n}_{best[n]}"], 2)] for n in w.QUERIES},
        "maintenance": maintenance(c, w),
        "build": {k: round(v, 2) for k, v in build.items()},
    }
    print(json.dumps(out))
    sys.stdout.flush()
    spark.stop()


if __name__ == "__main__":
    main()
