"""Runtime measures: time limits, ratios, and what an executed plan reports of itself."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame

#: Seconds after which a run counts as not finished, in the tables and in the scaling runs of the paper.
TIMEOUT_S, SCALING_TIMEOUT_S = 1_800, 900


def timed(make: Callable[[], DataFrame], timeout_s: float = TIMEOUT_S) -> dict:
    """Run a small result to its end: status ok, timeout or oom, seconds (None unless ok) and the rows.

    A run that is over its time is cancelled by its job group. Other errors are raised.
    """
    from pyspark import InheritableThread
    from pyspark.sql import SparkSession

    spark = SparkSession.active()
    context, group, out = spark.sparkContext, f"timed-{uuid.uuid4().hex}", {}

    def work() -> None:
        context.setJobGroup(group, "timed run", interruptOnCancel=True)
        began = time.perf_counter()
        try:
            out["rows"] = make().collect()
            out["seconds"] = time.perf_counter() - began
        except Exception as e:  # kept for the caller, who raises it
            out["error"] = e

    thread: threading.Thread = InheritableThread(target=work, daemon=True)
    thread.start()
    thread.join(timeout_s)
    if thread.is_alive():
        while thread.is_alive():  # between two jobs there is nothing to cancel yet
            context.cancelJobGroup(group)
            thread.join(0.5)
        if "seconds" not in out or out["seconds"] > timeout_s:
            return {"status": "timeout", "seconds": None, "rows": None}
    if "error" in out:
        if "OutOfMemory" in str(out["error"]):
            return {"status": "oom", "seconds": None, "rows": None}
        raise out["error"]
    return {"status": "ok"} | out


def speedup(off: float | None, on: float | None) -> float | None:
    """Seconds without an option over seconds with it; None where one of the runs did not finish."""
    return None if off is None or not on else off / on


def normalised(seconds: dict[int, float | None], base: int = 1) -> dict[int, float | None]:
    """Seconds of each granularity over those of the base."""
    return {k: None if v is None or not seconds.get(base) else v / seconds[base] for k, v in seconds.items()}


def same_count(counts: dict[str, int]) -> bool:
    """Whether all methods give one count."""
    return len(set(counts.values())) <= 1


def _nodes(plan) -> list:
    kind = plan.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return _nodes(plan.executedPlan())
    if kind.endswith("QueryStageExec"):
        return _nodes(plan.plan())
    out, children = [plan], plan.children()
    for i in range(children.size()):
        out += _nodes(children.apply(i))
    return out


def explain_cost(df: DataFrame) -> dict:
    """Execute df and sum up its plan: operators, rows of the largest join or generator, shuffled bytes and records,
    their replication (shuffled records over rows scanned) and skew (largest over mean rows of a shuffle's partitions)."""
    df.collect()
    rows, shuffled, records, scanned, skew = 0, 0, 0, 0, 1.0
    nodes = _nodes(df._jdf.queryExecution().executedPlan())
    for n in nodes:
        kind, metrics = n.getClass().getSimpleName(), n.metrics()
        value = lambda k, m=metrics: m.apply(k).value() if m.contains(k) else 0
        if "Join" in kind or "Generate" in kind:
            rows = max(rows, value("numOutputRows"))
        if "Scan" in kind:
            scanned += value("numOutputRows")
        if kind == "ShuffleExchangeExec":
            shuffled += value("shuffleBytesWritten")
            records += value("shuffleRecordsWritten")
            sizes = list(n.mapOutputStatisticsFuture().value().get().get().bytesByPartitionId()) if n.mapOutputStatisticsFuture().isCompleted() else []
            if sum(sizes):
                skew = max(skew, max(sizes) * len(sizes) / sum(sizes))
    return {"operators": len(nodes), "largest_intermediate_rows": rows, "shuffle_bytes": shuffled, "shuffle_records": records,
            "replication": records / scanned if scanned else None, "skew": skew}
