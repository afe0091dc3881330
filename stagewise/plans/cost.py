"""What the engine spent on a plan: exchanges and the bytes that went through them."""

from __future__ import annotations

from pyspark.sql import DataFrame


def _walk(node):
    yield node
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        inner = [node.executedPlan()]
    elif kind.endswith("QueryStageExec"):
        inner = [node.plan()]
    else:
        children = node.children()
        inner = [children.apply(i) for i in range(children.size())]
    for child in inner:
        yield from _walk(child)


def spent(df: DataFrame) -> dict[str, int]:
    """Run the frame, which must be small in rows, and count shuffles, broadcasts and their bytes; a reused exchange counts once."""
    df.collect()
    out = {"shuffles": 0, "shuffle_bytes": 0, "broadcasts": 0, "broadcast_bytes": 0}
    for node in _walk(df._jdf.queryExecution().executedPlan()):
        kind = node.getClass().getSimpleName()
        if kind in ("ShuffleExchangeExec", "BroadcastExchangeExec"):
            name, metric = ("shuffle", "shuffleBytesWritten") if kind.startswith("Shuffle") else ("broadcast", "dataSize")
            out[f"{name}s"] += 1
            out[f"{name}_bytes"] += node.metrics().apply(metric).value()
    return out
