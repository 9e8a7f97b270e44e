"""Path fronts as supersteps: all labels of all tasks in one state table.

State: (task_id, node, c0.., path, open). A superstep drops open labels that no completion can save (global domination),
extends the others along their edges, drops again before the shuffle, and keeps the front of every (task, node). For two
criteria the front is a running minimum over a sort; otherwise each group's vectors are compared once in an array.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dominance import set_dominates, vec_add, vec_max
from .loop import Trace, materialise, run_supersteps


def local_fronts(labels: DataFrame, d: int, ties: str = "all") -> DataFrame:
    """Rows (task_id, node, c0.., path, open) without those that another of their group dominates."""
    cost = [f"c{i}" for i in range(d)]
    if ties == "one":
        pick = F.struct(F.col("open"), F.size("path").alias("n"), "path")
        labels = labels.groupBy("task_id", "node", *cost).agg(F.min(pick).alias("pick")).select("task_id", "node", *cost, "pick.path", "pick.open")
    if d == 1:
        w = Window.partitionBy("task_id", "node")
        return labels.withColumn("least", F.min("c0").over(w)).where("c0 = least").drop("least")
    if d == 2:
        w = Window.partitionBy("task_id", "node").orderBy("c0", "c1")
        ranked = labels.withColumn("before", F.min("c1").over(w.rowsBetween(Window.unboundedPreceding, -1)))
        # equal vectors stand or fall with the first of them
        first = Window.partitionBy("task_id", "node", *cost)
        ranked = ranked.withColumn("best", F.max(F.when(F.col("before").isNull(), F.lit(True)).otherwise(F.col("c1") < F.col("before"))).over(first))
        return ranked.where("best").drop("before", "best")
    vec = F.array(*cost)
    w = Window.partitionBy("task_id", "node")
    return labels.withColumn("all", F.collect_set(vec).over(w)).where(~set_dominates(F.col("all"), vec)).drop("all")


def path_fronts(edges: DataFrame, tasks: DataFrame, d: int, bounds: DataFrame | None = None, anchors: DataFrame | None = None, *, tighten: bool = True, ties: str = "all", single_source: bool = False, max_hops: int | None = None, most: int = 10_000, limit_s: float | None = None) -> tuple[DataFrame, Trace]:
    """(task_id, node, c0.., path) of every target (or, single-source, of every node), and the loop's trace.

    bounds: (task_id, node, lb); a node without a bound is pruned; None means zero bounds. anchors: (task_id, cost) of known
    s-t paths, used for pruning from the start. max_hops, if given, is part of the question, not a cap on the answer.
    """
    cost = [f"c{i}" for i in range(d)]
    out_edges = materialise(edges.select("src", F.col("dst").alias("head"), *(F.col(c).alias(f"e{c}") for c in cost)).repartition("src"), "out-edges")
    ends = tasks.select("task_id", F.col("src").alias("source"), F.col("dst").alias("target"))
    zero = [F.lit(0).cast("long").alias(c) for c in cost]
    seed = tasks.select("task_id", F.col("src").alias("node"), *zero, F.array("src").alias("path"), (F.lit(single_source) | (F.col("src") != F.col("dst"))).alias("open"))
    lb = materialise(bounds.select("task_id", "node", "lb"), "lb") if bounds is not None else None
    given = anchors.groupBy("task_id").agg(F.collect_set("cost").alias("given")) if anchors is not None else None
    given = materialise(given, "given") if given is not None else None
    whole = lb.join(F.broadcast(ends.select("task_id", F.col("source").alias("node"))), ["task_id", "node"]).select("task_id", F.col("lb").alias("whole")) if lb is not None and tighten else None
    whole = materialise(whole, "whole") if whole is not None else None
    none = F.lit([]).cast("array<array<long>>")

    def rivals(state: DataFrame) -> DataFrame:
        at = state.join(F.broadcast(ends.select("task_id", F.col("target").alias("node"))), ["task_id", "node"]).groupBy("task_id").agg(F.collect_set(F.array(*cost)).alias("reached"))
        r = ends.join(at, "task_id", "left")
        r = r.join(given, "task_id", "left") if given is not None else r.withColumn("given", none)
        r = r.join(whole, "task_id", "left") if whole is not None else r.withColumn("whole", F.lit(None).cast("array<long>"))
        return r.select("task_id", "target", F.array_union(F.coalesce("reached", none), F.coalesce("given", none)).alias("rivals"), "whole")

    def alive(labels: DataFrame) -> DataFrame:
        """Labels (with target, rivals, whole) that may still become part of the answer."""
        vec = F.array(*cost)
        if lb is not None:
            labels = labels.join(lb, ["task_id", "node"])
            vec = vec_add(vec, F.col("lb"))
        vec = F.when(F.col("whole").isNull(), vec).otherwise(vec_max(vec, F.coalesce("whole", vec)))
        return labels.where(~set_dominates(F.col("rivals"), vec)).drop("lb")

    def step(state: DataFrame, k: int) -> DataFrame:
        going = state.where("open")
        if not single_source:
            going = alive(going.join(F.broadcast(rivals(state)), "task_id"))
        made = going.join(out_edges, going["node"] == out_edges["src"]).where(~F.array_contains("path", F.col("head")))
        if max_hops is not None:
            made = made.where(F.size("path") <= max_hops)
        keep = [] if single_source else ["target", "rivals", "whole"]
        made = made.select("task_id", F.col("head").alias("node"), *((F.col(c) + F.col(f"e{c}")).alias(c) for c in cost), F.array_append("path", F.col("head")).alias("path"), *keep)
        if not single_source:
            made = alive(made).withColumn("open", F.col("node") != F.col("target"))
        else:
            made = made.withColumn("open", F.lit(True))
        made = made.select("task_id", "node", *cost, "path", "open")
        both = state.withColumn("open", F.lit(False)).unionByName(made)
        return local_fronts(both.select("task_id", "node", *cost, "path", "open"), d, ties)

    state, trace = run_supersteps(seed, step, lambda s: s.where("open").count(), most=most, limit_s=limit_s, label="labels")
    if not single_source:
        state = state.join(F.broadcast(ends.select("task_id", F.col("target").alias("node"))), ["task_id", "node"])
    return state.select("task_id", "node", *cost, "path"), trace
