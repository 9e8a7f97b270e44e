"""Measures of the experiments: visited share, assembled paths, runtimes, front sizes, factors, hop bins, tightness."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def measure(result: DataFrame, nodes: int) -> DataFrame:
    """One row a task from a solver's result; nodes: nodes of the whole network."""
    pct = lambda c: F.col(c) * 100.0 / nodes
    return result.select(
        "task_id", "provider", "visited", pct("visited").alias("visited_pct"), pct("visited_bounds").alias("bound_visited_pct"), "paths_assembled", "paths_rejected", F.size("front").alias("front_size"), "bound_ms", "search_ms", "timed_out"
    )


def summary(measures: DataFrame, *keys: str) -> DataFrame:
    """Averages over tasks by provider (and keys), with time-outs counted; a timed-out task counts with what it had reached."""
    avg = lambda c: F.round(F.avg(c), 4).alias(c)
    return measures.groupBy(*keys, "provider").agg(F.count(F.lit(1)).alias("tasks"), *(avg(c) for c in ("visited_pct", "bound_visited_pct", "paths_assembled", "paths_rejected", "front_size", "bound_ms", "search_ms")), F.sum(F.col("timed_out").cast("int")).alias("timeouts"))


def compare(summaries: DataFrame, value: str, reference: str, *keys: str) -> DataFrame:
    """Adds factor = the reference provider's value / this provider's."""
    w = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))
    ref = F.max(F.when(F.col("provider") == reference, F.col(value))).over(w)
    return summaries.withColumn("factor", F.round(ref / F.when(F.col(value) != 0, F.col(value)), 2))


def by_hops(measures: DataFrame, hops: DataFrame, width: int, *keys: str) -> DataFrame:
    """Averages by provider and hop bin; hops: (task_id, hops)."""
    binned = measures.join(F.broadcast(hops), "task_id").withColumn("hop_bin", (F.floor(F.col("hops") / width) * width).cast("int"))
    return summary(binned, "hop_bin", *keys)


def tightness(bounds: dict[str, DataFrame], exact: DataFrame, d: int) -> DataFrame:
    """Sum of bounds / sum of exact costs per provider and criterion, over the nodes that the provider bounds."""
    out = None
    truth = exact.select("task_id", "node", F.col("lb").alias("exact"))
    for name, rows in bounds.items():
        j = rows.join(truth, ["task_id", "node"]).agg(*(F.round(F.sum(F.col("lb")[i]) / F.sum(F.col("exact")[i]), 6).alias(f"tightness{i}") for i in range(d)), F.count(F.lit(1)).alias("nodes")).select(F.lit(name).alias("provider"), "*")
        out = j if out is None else out.unionByName(j)
    return out


def run_timed(fn: Callable[[], object], repeats: int = 3, limit_s: float = 300.0) -> dict:
    """Mean wall time of `repeats` runs; a run beyond the limit counts with the limit."""
    took, late = [], 0
    for _ in range(repeats):
        began = time.perf_counter()
        fn()
        s = time.perf_counter() - began
        late += s > limit_s
        took.append(min(s, limit_s))
    return {"mean_s": sum(took) / len(took), "runs": repeats, "timeouts": late}
