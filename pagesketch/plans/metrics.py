"""What a plan really shuffled, from its own SQL metrics."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _nodes(node):
    """All physical nodes below, through adaptive plans and query stages."""
    name = node.getClass().getSimpleName()
    yield name, node
    if name == "AdaptiveSparkPlanExec":
        yield from _nodes(node.executedPlan())
    elif name.endswith("QueryStageExec"):
        yield from _nodes(node.plan())
    else:
        children = node.children()
        for i in range(children.size()):
            yield from _nodes(children.apply(i))


def shuffle_cost(df: DataFrame) -> dict[str, int]:
    """Runs df and returns the records and bytes its exchanges wrote, and the number of exchanges.

    An exchange that is reused counts once.
    """
    run = df._jdf.queryExecution()
    run.toRdd().count()
    out, seen = {"exchanges": 0, "records": 0, "bytes": 0}, set()
    for name, node in _nodes(run.executedPlan()):
        if name == "ShuffleExchangeExec" and (key := node.id()) not in seen:
            seen.add(key)
            out["exchanges"] += 1
            for metric, field in (("shuffleRecordsWritten", "records"), ("shuffleBytesWritten", "bytes")):
                out[field] += node.metrics().apply(metric).value()
    return out
