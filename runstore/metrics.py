"""What a finished query's operators counted: rows and bytes read, rows of join sides."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _children(node) -> list:
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return [node.executedPlan()]
    if kind.endswith("QueryStageExec"):
        return [node.plan()]
    seq = node.children()
    return [seq.apply(i) for i in range(seq.size())]


def operator_metrics(df: DataFrame) -> list[tuple[str, dict[str, int]]]:
    """(operator, its counters) of every node of the plan that ran; runs the frame once."""
    plan = df._jdf.queryExecution().executedPlan()
    plan.execute().count()
    out, todo = [], [plan]
    while todo:
        node = todo.pop()
        found = node.metrics()
        counters = {k: found.apply(k).value() for k in ("numOutputRows", "filesSize", "numFiles") if found.contains(k)}
        out.append((node.nodeName(), counters))
        todo += _children(node)
    return out


def scan_metrics(df: DataFrame) -> dict[str, int]:
    """Rows and bytes that the frame's scans read."""
    scans = [m for name, m in operator_metrics(df) if name.startswith("Scan")]
    return {"rows": sum(m.get("numOutputRows", 0) for m in scans), "bytes": sum(m.get("filesSize", 0) for m in scans)}
