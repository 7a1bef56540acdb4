"""What a question costs: time, joins, shuffles and rows, read from its executed plan."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame

_COUNTED = {"joins": ("Join",), "scans": ("Scan", "FileScan"), "exchanges": ("Exchange",), "windows": ("Window",)}


def _nodes(node) -> list:
    """All operators of an executed physical plan, those inside query stages included."""
    name = node.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        return _nodes(node.executedPlan())
    if name.endswith("QueryStageExec"):
        return _nodes(node.plan())
    below, children = [], node.children()
    for k in range(children.size()):
        below += _nodes(children.apply(k))
    return [node, *below]


def _metric(node, name: str) -> int:
    held = node.metrics().get(name)
    return int(held.get().value()) if held.isDefined() else 0


def measure(df: DataFrame) -> dict[str, float]:
    """Runs ``df`` and gives {seconds, joins, scans, exchanges, windows, shuffled_bytes, rows_read}; results are thrown away, and so is what it shuffled.

    A reused exchange counts once. The plan is the one that ran, after adaptive changes.
    """
    began = time.time()
    executed = df._jdf.queryExecution().executedPlan()
    # Collecting the count of the same plan's rows would change the plan, so its own rows are drained on the executors.
    df._jdf.queryExecution().toRdd().count()
    seconds = time.time() - began
    nodes = _nodes(executed)
    names = [n.nodeName() for n in nodes]
    out: dict[str, float] = {k: sum(any(p in name for p in parts) and "Reused" not in name and not (k == "joins" and "Exchange" in name) for name in names) for k, parts in _COUNTED.items()}
    out["shuffled_bytes"] = sum(_metric(n, "shuffleBytesWritten") for n, name in zip(nodes, names, strict=True) if "Exchange" in name and "Reused" not in name)
    out["rows_read"] = sum(_metric(n, "numOutputRows") for n, name in zip(nodes, names, strict=True) if "Scan" in name)
    out["seconds"] = round(seconds, 3)
    # Else shuffles stay on disk until the driver's next garbage collection, and all questions' add up.
    cleaner = df.sparkSession.sparkContext._jsc.sc().cleaner()
    if cleaner.isDefined():
        for n, name in zip(nodes, names, strict=True):
            if name == "Exchange":
                cleaner.get().doCleanupShuffle(n.shuffleId(), True)
    return out


def compared(questions: dict[str, dict[str, DataFrame]]) -> list[tuple]:
    """(question, executor, joins, scans, exchanges, shuffled_bytes, rows_read, seconds) of each question under each executor."""
    rows = []
    for q, ways in questions.items():
        for way, df in ways.items():
            m = measure(df)
            rows.append((q, way, *(int(m[k]) for k in ("joins", "scans", "exchanges", "shuffled_bytes", "rows_read")), float(m["seconds"])))
    return rows
