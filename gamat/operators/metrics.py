"""Measures: speedup, scaling, communication, balance, synchronisation, error."""

from __future__ import annotations

import re
import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Calls a user must know: the two functions of this engine, against one per operation and structure in a library column.
ENTRY_POINTS = {"gather/apply": 2, "one library column": 13}


def timed(make, runs: int = 3) -> float:
    """Median seconds of warm runs that write nowhere."""
    make().write.format("noop").mode("overwrite").save()
    out = []
    for _ in range(runs):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        out.append(time.time() - began)
    return median(out)


def speedup(baseline: float, ours: float) -> float:
    return baseline / ours


def matrix_share(matrix_seconds: float, total_seconds: float) -> float:
    return matrix_seconds / total_seconds


def shares(steps: dict[str, tuple], runs: int = 1) -> dict[str, float]:
    """Share of all time that each named step takes; steps: name -> (function that makes a DataFrame, whether it is a matrix
    operation). "matrix operations" sums the latter."""
    took = {n: timed(make, runs) for n, (make, _) in steps.items()}
    total = sum(took.values())
    out = {n: t / total for n, t in took.items()}
    return out | {"matrix operations": sum(took[n] for n, (_, is_matrix) in steps.items() if is_matrix) / total}


def shuffled(df: DataFrame) -> tuple[int, int]:
    """(rows, bytes) that a run of df writes into shuffles, from the plan's own counters."""
    df.foreach(_nothing)
    text, rows, size = [df._jdf.queryExecution().executedPlan()], 0, 0
    while text:
        node = text.pop()
        name = node.nodeName()
        inner = node.executedPlan() if name == "AdaptiveSparkPlan" else node.plan() if "QueryStage" in name else None
        if inner is not None:
            text.append(inner)
            continue
        if name == "Exchange":
            metrics = node.metrics()
            rows += metrics.apply("shuffleRecordsWritten").value()
            size += metrics.apply("shuffleBytesWritten").value()
        children = node.children()
        text += [children.apply(i) for i in range(children.size())]
    return rows, size


def _nothing(row) -> None:
    """Takes a row and does nothing with it."""


def exchanges(df: DataFrame) -> int:
    """Exchanges in the initial physical plan: what must wait for everything before it."""
    text = df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "simple")
    return len(re.findall(r"(?<!Broadcast)(?<!Reused)Exchange (?:hash|range|Single|RoundRobin)", text))


def error(got: DataFrame, reference: DataFrame, keys: list[str], value: str) -> DataFrame:
    """max_abs, max_rel: largest differences; a cell that one side lacks counts as zero there."""
    r = reference.select(*keys, F.col(value).cast("double").alias("__r"))
    both = got.select(*keys, F.col(value).cast("double").alias("__g")).join(r, keys, "full")
    g, t = F.coalesce("__g", F.lit(0.0)), F.coalesce("__r", F.lit(0.0))
    return both.agg(F.max(F.abs(g - t)).alias("max_abs"), F.max(F.when(t != 0, F.abs(g - t) / F.abs(t))).alias("max_rel"))
