"""Bound sweeps as supersteps over all tasks of a batch at once.

State: (task_id, node, w0..w{d-1}, open). w_i is a struct (value, total, next, vec): the least value of criterion i of any
walk that reached the node, with the walk's total, its first node, and its whole cost vector (the witness). Minima of
structs carry all four along, so a superstep is one join with the edges and one aggregation. Absent rows mean infinity.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.dominance import set_dominates, vec_add, vec_min
from . import blocks
from .loop import Trace, materialise, run_supersteps


@dataclass
class BoundResult:
    """lb (task_id, node, lb), anchors (task_id, criterion, cost), visited (task_id, node), and the loop's trace."""

    state: DataFrame
    tasks: DataFrame
    d: int
    trace: Trace

    @property
    def lb(self) -> DataFrame:
        return self.state.select("task_id", "node", F.array(*(F.col(f"w{i}.value") for i in range(self.d))).alias("lb"))

    @property
    def visited(self) -> DataFrame:
        return self.state.select("task_id", "node")

    @property
    def anchors(self) -> DataFrame:
        """Current optimum of each criterion, where the target can be reached."""
        at = self.state.join(self.tasks.select("task_id", F.col("src").alias("node")), ["task_id", "node"])
        return at.select("task_id", F.posexplode(F.array(*(F.col(f"w{i}.vec") for i in range(self.d)))).alias("criterion", "cost"))

    def paths(self, criterion: int, most: int = 10_000) -> DataFrame:
        """(task_id, path) of one criterion's optimum: follow stored next nodes from the source, all tasks together."""
        nxt = self.state.select("task_id", "node", F.col(f"w{criterion}.next").alias("next"))
        start = self.tasks.select("task_id", "dst", F.array("src").alias("path"), F.col("src").alias("at")).join(self.state.select("task_id", F.col("node").alias("at")), ["task_id", "at"], "left_semi")
        opened = start.withColumn("open", F.col("at") != F.col("dst"))

        def step(s: DataFrame, k: int) -> DataFrame:
            more = s.join(nxt.withColumnRenamed("node", "at"), ["task_id", "at"], "left")
            at = F.when(F.col("open"), F.col("next")).otherwise(F.col("at"))
            return more.select("task_id", "dst", F.when(F.col("open"), F.array_append("path", F.col("next"))).otherwise(F.col("path")).alias("path"), at.alias("at"), (at != F.col("dst")).alias("open"))

        done, _ = run_supersteps(opened.select("task_id", "dst", "path", "at", "open"), step, lambda s: s.where("open").count(), most=most, label="paths")
        return done.select("task_id", "path")


def _costs(d: int) -> list[str]:
    return [f"c{i}" for i in range(d)]


def _edges(edges: DataFrame, backward: bool) -> DataFrame:
    """(from_, to_, c..): the sweep runs from from_ to to_."""
    a, b = ("dst", "src") if backward else ("src", "dst")
    return edges.withColumnsRenamed({a: "from_", b: "to_"})


def _walk(value: Column, total: Column, nxt: Column, vec: Column) -> Column:
    return F.struct(value.alias("value"), total.alias("total"), nxt.alias("next"), vec.alias("vec"))


def _seed(tasks: DataFrame, end: str, d: int) -> DataFrame:
    zero = F.lit(0).cast("long")
    start = _walk(zero, zero, F.lit(-1).cast("long"), F.array(*[zero] * d))
    return tasks.select("task_id", F.col(end).alias("node"), *(start.alias(f"w{i}") for i in range(d)), F.lit(True).alias("open"))


def sweep(edges: DataFrame, tasks: DataFrame, d: int, *, backward: bool = True, prune: bool = False, order: str = "all", delta: int = 500, stop: str = "none", ceiling: DataFrame | None = None, expand_end: bool = False, most: int = 10_000, limit_s: float | None = None) -> BoundResult:
    """Label-correcting sweep of every task from its target (or, forward, from its source).

    prune: drop an open node whose vector is dominated by a known s-t walk (one-pass bounds; without it the result is that
    of full searches). order: 'all' open nodes a superstep, or 'bucket' (those within `delta` of the least sum).
    stop: 'source' closes nodes that are not better than the far end in any criterion; 'ceiling' those above
    `ceiling` (task_id, ceilings array) in every criterion.
    """
    start, end = ("dst", "src") if backward else ("src", "dst")
    graph = _edges(edges.select("src", "dst", *_costs(d)), backward).repartition("from_")
    graph = materialise(graph, "edges")
    if expand_end and not prune and order == "all" and stop == "none":
        bits, count = blocks.bits_of(graph, d)
        if bits is not None:
            state, trace = blocks.full_sweep(graph, _seed(tasks, start, d), d, bits, count, most=most, limit_s=limit_s)
            return BoundResult(state, tasks, d, trace)
    ends = tasks.select("task_id", F.col(start).alias("start"), F.col(end).alias("end"))
    lb = F.array(*(F.col(f"w{i}.value") for i in range(d)))

    def step(state: DataFrame, k: int) -> DataFrame:
        frontier = state.where("open").join(F.broadcast(ends), "task_id").where((F.col("node") != F.col("end")) | F.lit(expand_end))
        if order == "bucket":
            least = frontier.groupBy("task_id").agg(F.min(sum((F.col(f"w{i}.value") for i in range(d)), F.lit(0))).alias("least"))
            frontier = frontier.join(F.broadcast(least), "task_id").withColumn("now", sum((F.col(f"w{i}.value") for i in range(d)), F.lit(0)) <= F.col("least") + delta)
        else:
            frontier = frontier.withColumn("now", F.lit(True))
        going = frontier.where("now")
        if prune or stop == "source":
            far = state.join(F.broadcast(ends.select("task_id", F.col("end").alias("node"))), ["task_id", "node"]).select("task_id", F.array(*(F.col(f"w{i}.vec") for i in range(d))).alias("anchors"), lb.alias("far"))
            going = going.join(F.broadcast(far), "task_id", "left")
            if prune:
                going = going.where(F.col("anchors").isNull() | ~set_dominates(F.col("anchors"), lb))
            else:
                going = going.where(F.col("far").isNull() | F.exists(F.zip_with(lb, "far", lambda x, y: x < y), lambda z: z))
        if stop == "ceiling":
            going = going.join(F.broadcast(ceiling), "task_id").where(F.exists(F.zip_with(lb, "ceilings", lambda x, y: x <= y), lambda z: z))
        total = sum((F.col(c) for c in _costs(d)), F.lit(0))
        edge_vec = F.array(*_costs(d))
        made = going.join(graph, F.col("node") == F.col("from_")).where(F.col("to_") != F.col("start"))
        made = made.select(
            "task_id", F.col("to_").alias("node"), *(_walk(F.col(f"w{i}.value") + F.col(f"c{i}"), F.col(f"w{i}.total") + total, F.col("from_"), vec_add(F.col(f"w{i}.vec"), edge_vec)).alias(f"w{i}") for i in range(d)), F.lit(True).alias("fresh"), F.lit(False).alias("waits")
        )
        waiting = state.select("task_id", "node", *(f"w{i}" for i in range(d)), F.lit(False).alias("fresh"), F.col("open").alias("was"))
        if order == "bucket":
            waiting = waiting.join(frontier.where(~F.col("now")).select("task_id", "node", F.lit(True).alias("waits")), ["task_id", "node"], "left").drop("was").withColumn("waits", F.coalesce("waits", F.lit(False)))
        else:
            waiting = waiting.drop("was").withColumn("waits", F.lit(False))
        both = waiting.unionByName(made)
        old = [F.min(F.when(~F.col("fresh"), F.col(f"w{i}"))).alias(f"o{i}") for i in range(d)]
        new = both.groupBy("task_id", "node").agg(*(F.min(f"w{i}").alias(f"w{i}") for i in range(d)), *old, F.max("waits").alias("waits"))
        better = F.lit(False)
        for i in range(d):
            better = better | F.col(f"o{i}").isNull() | (F.struct(F.col(f"w{i}.value"), F.col(f"w{i}.total")) < F.struct(F.col(f"o{i}.value"), F.col(f"o{i}.total")))
        return new.select("task_id", "node", *(f"w{i}" for i in range(d)), (better | F.col("waits")).alias("open"))

    state, trace = run_supersteps(_seed(tasks, start, d), step, lambda s: s.where("open").count(), most=most, limit_s=limit_s, label="sweep")
    return BoundResult(state, tasks, d, trace)


def multi_bounds(edges: DataFrame, tasks: DataFrame, d: int, **options) -> BoundResult:
    """Full searches: the source is passed through too, and blocks of nodes are searched at once (`blocks`)."""
    return sweep(edges, tasks, d, prune=False, expand_end=True, **options)


def onepass_bounds(edges: DataFrame, tasks: DataFrame, d: int, prune: bool = True, **options) -> BoundResult:
    return sweep(edges, tasks, d, prune=prune, **options)


def reverse_costs(edges: DataFrame, tasks: DataFrame, criterion: str, **options) -> BoundResult:
    """Single-criterion costs to every task's target; edges carry named cost columns."""
    return sweep(edges.select("src", "dst", F.col(criterion).cast("long").alias("c0")), tasks, 1, **options)


def forward_costs(edges: DataFrame, tasks: DataFrame, criterion: str, **options) -> BoundResult:
    return sweep(edges.select("src", "dst", F.col(criterion).cast("long").alias("c0")), tasks, 1, backward=False, **options)


def hops(edges: DataFrame, tasks: DataFrame, **options) -> BoundResult:
    return sweep(edges.select("src", "dst", F.lit(1).cast("long").alias("c0")), tasks, 1, **options)


def twosided_bounds(edges: DataFrame, tasks: DataFrame, d: int, *, most: int = 10_000, limit_s: float | None = None) -> BoundResult:
    """Backward and forward sweeps in lockstep until a task's sides meet; then backward only, with the sharper filter.

    Each task has its own phase: sides meet at different supersteps. Bounds are those of the backward side.
    """
    graph = materialise(_edges(edges.select("src", "dst", *_costs(d)), True).select(F.lit("b").alias("side"), "from_", "to_", *_costs(d)).unionByName(_edges(edges.select("src", "dst", *_costs(d)), False).select(F.lit("f").alias("side"), "from_", "to_", *_costs(d))).repartition("from_"), "edges2")
    lb = F.array(*(F.col(f"w{i}.value") for i in range(d)))
    names = [f"w{i}" for i in range(d)]
    zero = F.array(*[F.lit(0).cast("long")] * d)
    ends = tasks.select("task_id", "src", "dst")
    seed = _seed(tasks, "dst", d).withColumn("side", F.lit("b")).unionByName(_seed(tasks, "src", d).withColumn("side", F.lit("f")))
    empty = F.lit(None).cast("array<array<long>>")
    seed = seed.select("task_id", "side", "node", *names, "open", empty.alias("anchors"), F.lit(None).cast("array<long>").alias("floor"), F.lit(False).alias("met"))

    def step(state: DataFrame, k: int) -> DataFrame:
        # what each task knows: where its sides met, the walks found there and at the source, the least open forward vector
        back, fore = state.where("side = 'b'"), state.where("side = 'f'")
        join = back.select("task_id", "node", *(F.col(n).alias(f"b{n}") for n in names)).join(fore.select("task_id", "node", *names), ["task_id", "node"])
        walks = join.select("task_id", F.explode(F.array(*(vec_add(F.col(f"b{n}.vec"), F.col(f"{n}.vec")) for n in names))).alias("walk"))
        walks = walks.groupBy("task_id").agg(F.collect_set("walk").alias("new"))
        floor = fore.where("open").groupBy("task_id").agg(F.array(*(F.min(f"{n}.value") for n in names)).alias("open_floor"))
        kept = state.groupBy("task_id").agg(F.max("met").alias("was"), F.first("anchors", True).alias("old"), F.first("floor", True).alias("old_floor"))
        at_source = back.join(F.broadcast(ends.select("task_id", F.col("src").alias("node"))), ["task_id", "node"]).select("task_id", F.array(*(F.col(f"{n}.vec") for n in names)).alias("source_walks"))
        known = kept.join(walks, "task_id", "left").join(floor, "task_id", "left").join(at_source, "task_id", "left")
        none = F.lit([]).cast("array<array<long>>")
        known = known.select(
            "task_id",
            (F.col("was") | F.col("new").isNotNull()).alias("met"),
            F.when(F.col("was"), F.array_union(F.coalesce("old", none), F.coalesce("source_walks", none))).otherwise(F.array_union(F.coalesce("new", none), F.coalesce("source_walks", none))).alias("anchors"),
            F.when(F.col("was"), F.col("old_floor")).when(F.col("new").isNotNull(), F.coalesce("open_floor", zero)).alias("floor"),
        )
        now = state.drop("met", "anchors", "floor").join(F.broadcast(known), "task_id").join(F.broadcast(ends), "task_id")
        before = fore.select("task_id", "node", lb.alias("fore_lb"))
        going = now.where("open").where(~(F.col("met") & (F.col("side") == "f"))).where((F.col("side") == "f") | (F.col("node") != F.col("src")))
        going = going.join(before, ["task_id", "node"], "left")
        reach = vec_add(lb, F.when(F.col("fore_lb").isNull(), F.col("floor")).otherwise(vec_min(F.col("fore_lb"), F.col("floor"))))
        going = going.where(~F.col("met") | (F.col("side") == "f") | ~set_dominates(F.col("anchors"), reach))
        total = sum((F.col(c) for c in _costs(d)), F.lit(0))
        made = going.join(graph, (going["node"] == graph["from_"]) & (going["side"] == graph["side"])).drop(graph["side"])
        made = made.where(F.col("to_") != F.when(F.col("side") == "b", F.col("dst")).otherwise(F.col("src")))
        made = made.select("task_id", "side", F.col("to_").alias("node"), *(_walk(F.col(f"w{i}.value") + F.col(f"c{i}"), F.col(f"w{i}.total") + total, F.col("from_"), vec_add(F.col(f"w{i}.vec"), F.array(*_costs(d)))).alias(f"w{i}") for i in range(d)), F.lit(True).alias("fresh"))
        both = state.select("task_id", "side", "node", *names, F.lit(False).alias("fresh")).unionByName(made)
        new = both.groupBy("task_id", "side", "node").agg(*(F.min(n).alias(n) for n in names), *(F.min(F.when(~F.col("fresh"), F.col(n))).alias(f"o{n}") for n in names))
        better = F.lit(False)
        for n in names:
            better = better | F.col(f"o{n}").isNull() | (F.struct(F.col(f"{n}.value"), F.col(f"{n}.total")) < F.struct(F.col(f"o{n}.value"), F.col(f"o{n}.total")))
        out = new.withColumn("better", better).join(F.broadcast(known), "task_id")
        # after the meeting the forward side rests; its open nodes stay open for the floor only at the meeting itself
        return out.select("task_id", "side", "node", *names, (F.col("better") & ~(F.col("met") & (F.col("side") == "f"))).alias("open"), "anchors", "floor", "met")

    def open_count(s: DataFrame) -> int:
        # a task whose forward side ran dry before meeting can't be answered; a task is alive while its backward side is open
        alive = s.groupBy("task_id").agg(F.max(F.when((F.col("side") == "b") & F.col("open"), 1).otherwise(0)).alias("b"), F.max(F.when((F.col("side") == "f") & F.col("open"), 1).otherwise(0)).alias("f"), F.max("met").alias("met"))
        return alive.where("b = 1 AND (met OR f = 1)").count()

    state, trace = run_supersteps(seed, step, open_count, most=most, limit_s=limit_s, label="twosided")
    result = BoundResult(state.where("side = 'b'").select("task_id", "node", *names, "open"), tasks, d, trace)
    result.both_sides = state.select("task_id", "node").distinct()
    return result
