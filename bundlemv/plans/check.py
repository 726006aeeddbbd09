"""What a plan moves: exchanges counted on the plan that ran."""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame


def _children(node) -> list:
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return [node.executedPlan()]
    if kind in ("ShuffleQueryStageExec", "BroadcastQueryStageExec", "ResultQueryStageExec"):
        return [node.plan()]
    if kind in ("TableCacheQueryStageExec", "InMemoryTableScanExec"):
        return []  # what was kept is not moved again
    seq = node.children()
    return [seq.apply(i) for i in range(seq.size())]


def moved(df: DataFrame) -> Counter:
    """Counts of ShuffleExchangeExec, BroadcastExchangeExec and the like; reused exchanges count as reused. Runs ``df`` first."""
    df.write.format("noop").mode("overwrite").save()
    execution = df._jdf.queryExecution()
    out: Counter = Counter()
    stack = [execution.executedPlan()]
    while stack:
        node = stack.pop()
        kind = node.getClass().getSimpleName()
        if "Exchange" in kind:
            out[kind] += 1
        if kind != "ReusedExchangeExec":
            stack += _children(node)
    return out


def shuffles(df: DataFrame) -> int:
    return moved(df)["ShuffleExchangeExec"]
