"""What a finished query did, from Spark's own metrics: rows and bytes that scans read, and what was shuffled, broadcast or spilled."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _nodes(plan):
    """All nodes of an executed plan, stages of adaptive execution included."""
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _nodes(plan.executedPlan())
    elif name.endswith("QueryStageExec"):
        yield from _nodes(plan.plan())
    else:
        yield name, plan
        kids = plan.children().iterator()
        while kids.hasNext():
            yield from _nodes(kids.next())


def spark_counters(df: DataFrame) -> list[tuple[str, str, int]]:
    """Runs the query; (node, what, how much) of every metric that isn't 0, nodes in the order of the plan."""
    df._jdf.collectToPython()
    out = []
    for i, (name, node) in enumerate(_nodes(df._jdf.queryExecution().executedPlan())):
        metrics = node.metrics().iterator()
        while metrics.hasNext():
            pair = metrics.next()
            if (value := int(pair._2().value())) > 0:
                out.append((f"{i} {name}", str(pair._1()), value))
    return out


def total(counters: list[tuple[str, str, int]], node: str, what: str) -> int:
    return sum(v for n, w, v in counters if node in n and w == what)
