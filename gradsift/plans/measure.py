"""What a plan really exchanged, read from the metrics of the plan that ran."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _walk(plan):
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _walk(plan.executedPlan())
        return
    if name.endswith("QueryStageExec"):
        yield from _walk(plan.plan())
        return
    yield plan
    for i in range(plan.children().size()):
        yield from _walk(plan.children().apply(i))


def exchanged(df: DataFrame) -> list[tuple[int, int]]:
    """(records, bytes) that each shuffle of ``df`` wrote; runs the plan, whose result must be small."""
    df._jdf.queryExecution().executedPlan().executeCollect()
    out = []
    for node in _walk(df._jdf.queryExecution().executedPlan()):
        if node.getClass().getSimpleName() == "ShuffleExchangeExec":
            metric = lambda name, node=node: int(node.metrics().apply(name).value())
            out.append((metric("shuffleRecordsWritten"), metric("shuffleBytesWritten")))
    return out
