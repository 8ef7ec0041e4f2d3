"""Physical measures: what a finished plan moved, from Spark's own metrics."""

from __future__ import annotations

from pyspark.sql import DataFrame

# Spark's metric names and ours.
METRICS = {"shuffleBytesWritten": "shuffle_bytes", "shuffleRecordsWritten": "shuffle_rows", "spillSize": "spill_bytes", "filesSize": "scan_bytes", "numFiles": "scan_files", "dataSize": "exchanged_bytes"}


def _nodes(plan):
    """A plan's nodes, through adaptive plans and finished query stages."""
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _nodes(plan.executedPlan())
        return
    if name.endswith("QueryStageExec"):
        yield from _nodes(plan.plan())
        return
    if name == "ReusedExchangeExec":
        return  # what it reads was counted where it was made
    yield name, plan
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def physical(df: DataFrame) -> dict[str, int]:
    """Runs a frame's count and returns it with exchanges, broadcasts and the sums of METRICS over the final plan."""
    counted = df.groupBy().count()
    plan_ = counted._jdf.queryExecution().executedPlan()
    out = {"rows": int(plan_.executeCollect()[0].getLong(0)), "exchanges": 0, "broadcasts": 0} | dict.fromkeys(METRICS.values(), 0)
    for name, plan in _nodes(plan_):
        out["exchanges"] += name == "ShuffleExchangeExec"
        out["broadcasts"] += name == "BroadcastExchangeExec"
        for metric, ours in METRICS.items():
            found = plan.metrics().get(metric)
            if found.isDefined():
                out[ours] += max(0, found.get().value())
    return out
