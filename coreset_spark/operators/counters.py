"""What a query's own counters say after it ran: rows, pairs and bytes shuffled, to set beside the printed costs."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _each(seq):
    it = seq.iterator()
    while it.hasNext():
        yield it.next()


def plan_metrics(df: DataFrame) -> list[dict]:
    """Runs the query and reads its final plan: a dict of node, metric and value each. The rows stay on the executors."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    out: list[dict] = []

    def walk(plan) -> None:
        name = plan.nodeName()
        if name.startswith("AdaptiveSparkPlan"):
            return walk(plan.executedPlan())
        if "QueryStage" in name:
            return walk(plan.plan())
        for pair in _each(plan.metrics()):
            metric = pair._2()
            out.append({"node": name, "metric": metric.name().get() if metric.name().isDefined() else pair._1(), "value": int(metric.value())})
        for child in _each(plan.children()):
            walk(child)

    walk(execution.executedPlan())
    return out


def total(metrics: list[dict], metric: str, node: str = "") -> int:
    return sum(x["value"] for x in metrics if x["metric"] == metric and node in x["node"])


def largest(metrics: list[dict], metric: str = "number of output rows", node: str = "") -> int:
    return max((x["value"] for x in metrics if x["metric"] == metric and node in x["node"]), default=0)
