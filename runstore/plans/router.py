"""One entry for queries: picks views, runs, a hybrid or columns by what each would move, and says why."""

from __future__ import annotations

from pyspark.sql import DataFrame

from runstore import cost
from runstore.operators import runs
from runstore.plans import baselines, rewrite, sqltext, views
from runstore.spec import SortedProjection, StarQuery, StrategyPlan, ViewDefinition

STRATEGIES = ("auto", "views", "runs", "runs_nocollapse", "hybrid", "columnar", "row", "vertical", "index")


class Engine:
    """Answers star queries by the strategy that moves the fewest bytes (`cost.estimates`) among those whose rules admit them.

    exact: queries whose answers are stored with their constants; these are
    served from there and come first.  SQL text of the class goes through the
    same choice; other text is plain Spark SQL over the base tables, and over
    the run tables and views that it names (`run_...`, `view_...`).
    """

    def __init__(self, catalog, projections: list[SortedProjection], definitions: list[ViewDefinition], exact: dict[str, StarQuery] | None = None):
        self.catalog, self.projections, self.definitions, self.exact = catalog, projections, definitions, exact or {}

    def pick_projection(self, q: StarQuery) -> SortedProjection | None:
        """The covering projection whose sort prefix the comparisons confine most; then the shallowest."""
        def confined(p: SortedProjection) -> int:
            k = 0
            for c in p.sort_cols:
                mine = [x for x in q.preds if x.col == c]
                if not mine:
                    break
                k += 1
                if not any(x.op == "=" for x in mine):
                    break
            return k

        covering = [p for p in self.projections if p.covers(q)]
        key = lambda p: (-confined(p), max((p.depth(c) for c in q.needed), default=0), len(p.sort_cols), p.name)
        return min(covering, key=key, default=None)

    def pick_partial(self, q: StarQuery) -> tuple[SortedProjection, str] | None:
        """A projection of the same joins that holds a compared leading column and a column of the query's rows to tell them by."""
        for p in self.projections:
            known = {x.col for x in q.preds} & set(p.sort_cols)
            shared = [c for c in p.sort_cols if c in q.columns]
            if p.aligned and p.base == q.base and set(p.joins) == set(q.joins) and p.sort_cols[0] in known and shared:
                return p, shared[0]
        return None

    def pick_view(self, q: StarQuery) -> tuple[ViewDefinition | None, list[str]]:
        """The matching view of fewest group columns, and why the others do not match."""
        reasons = [(v, views.match_view(q, v)) for v in self.definitions]
        fit = [v for v, why in reasons if not why]
        return min(fit, key=lambda v: (len(v.groups), v.name), default=None), [f"{v.name}: {why}" for v, why in reasons if why]

    def plan(self, q: StarQuery) -> StrategyPlan:
        for name, held in self.exact.items():
            if held == q:
                return StrategyPlan("exact", name)
        v, reasons = self.pick_view(q)
        p = self.pick_projection(q)
        partial = None if p is not None else self.pick_partial(q)
        moved = cost.estimates(self.catalog, q, p, v, partial[0] if partial else None)
        best = min(moved, key=lambda s: (moved[s], s))
        source = {"views": v.name if v else "", "runs": p.name if p else "", "hybrid": partial[0].name if partial else ""}.get(best, "")
        if p is None:
            reasons.append("no projection covers the columns")
        reasons += [f"{s}: {b / moved[best]:.1f} times the bytes" for s, b in sorted(moved.items()) if s != best and moved[best]]
        share = cost._share(self.catalog, p, q) if p is not None else None
        return StrategyPlan(best, source, "; ".join(reasons), share, moved)

    def query(self, q: StarQuery | str, strategy: str = "auto") -> DataFrame:
        """A query of the class, or SQL text; text outside the class runs as plain Spark SQL."""
        if strategy not in STRATEGIES:
            raise ValueError(f"unknown strategy {strategy}")
        if isinstance(q, str):
            parsed = sqltext.parse(q)
            if parsed is None:
                self.register(q)
                return self.catalog.spark.sql(q)
            q = parsed
        plan = self.plan(q) if strategy == "auto" else StrategyPlan(strategy)
        match plan.strategy:
            case "exact":
                return views.materialize_exact(self.catalog, q, plan.source)
            case "views":
                v, reasons = self.pick_view(q)
                if v is None:
                    raise ValueError("no view answers the query: " + "; ".join(reasons))
                return views.answer_from_view(self.catalog, q, v)
            case "row":
                return baselines.run_row(self.catalog, q)
            case "columnar":
                return baselines.run_columnar(self.catalog, q)
            case "hybrid":
                partial = self.pick_partial(q)
                if partial is None:
                    raise ValueError("no projection holds a compared leading column and an output column of the query")
                return baselines.run_hybrid(self.catalog, q, *partial)
        p = self.pick_projection(q)
        if p is None:
            raise ValueError("no projection covers the query")
        if plan.strategy == "vertical":
            return baselines.run_vertical(self.catalog, q, p)
        if plan.strategy == "index":
            return baselines.run_index(self.catalog, q, p)
        return rewrite.rewrite_runs(self.catalog, q, p, collapsing=plan.strategy != "runs_nocollapse")

    def register(self, text: str | None = None) -> None:
        """Base tables, and run tables and views (those that a text names, else all), as temporary views of the session."""
        from runstore.catalog import SCHEMAS

        named = (lambda x: True) if text is None else (lambda x: x.lower() in text.lower())
        for name in SCHEMAS:
            self.catalog.table(name).createOrReplaceTempView(name)
        for p in self.projections:
            if p.aligned and named(f"run_{p.name}_"):
                for c, t in runs.build_runs(self.catalog, p).items():
                    t.frame.createOrReplaceTempView(f"run_{p.name}_{c}")
        for v in self.definitions:
            if named(f"view_{v.name}"):
                views.build_view(self.catalog, v).createOrReplaceTempView(f"view_{v.name}")
