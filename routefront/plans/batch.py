"""Many tasks in one job: the kernel for networks of a checked size, supersteps beyond it."""

from __future__ import annotations

import inspect
import math
import time
import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.networks import project
from . import arrays as arrays_
from . import kernel, labels, settled, sweep
from .loop import materialise

RESULT = (
    "task_id long, src long, dst long, provider string, visited_bounds long, visited_search long, visited long, paths_assembled long, paths_rejected long, bound_ms double, search_ms double, timed_out boolean, "
    "front array<struct<cost:array<long>,path:array<long>>>, best array<struct<criterion:int,cost:array<long>,path:array<long>>>"
)


def graph_arrays(edges: DataFrame, limit: int | None = None):
    """Edges (src, dst, c0..) as numpy arrays, sorted, if they are at most `limit` (EDGE_LIMIT), else None."""
    names = edges.columns
    cost = [c for c in names if c not in ("src", "dst")]
    range_ = edges.agg(F.count(F.lit(1)).alias("n"), F.max(F.greatest(*names)).alias("most"), F.min(F.least(*names)).alias("least")).first()
    if range_["n"] > (kernel.EDGE_LIMIT if limit is None else limit):
        return None
    small = range_["n"] and range_["most"] < 1 << 31 and range_["least"] >= -(1 << 31)
    got = edges.select(*(F.col(c).cast("int" if small else "long").alias(c) for c in names)).toArrow()  # at most `limit` rows, as just counted
    col = {c: got.column(c).to_numpy() for c in names}
    del got
    order = np.lexsort([col[c] for c in [*reversed(cost), "dst", "src"]])
    out = np.empty((len(order), len(cost)), col["src"].dtype)
    for k, c in enumerate(cost):
        out[:, k] = col.pop(c)[order]
    return col["src"][order], col["dst"][order], out


_graphs: dict = {}


class _Shared:
    """A broadcast network with a name of its own, by which a worker keeps its adjacency."""

    def __init__(self, spark, arrays):
        self.name, self.arrays = uuid.uuid4().hex, spark.sparkContext.broadcast(arrays if isinstance(arrays, kernel.Graph) else kernel.Graph(*arrays))

    @property
    def graph(self) -> kernel.Graph:
        if self.name not in _graphs:
            _graphs.clear()
            _graphs[self.name] = self.arrays.value
        return _graphs[self.name]


def _spread(tasks: DataFrame, n: int | None = None) -> DataFrame:
    """Tasks in no particular order, cut into n parts of equal numbers: a few of them never share one while others are empty."""
    n = n or tasks.sparkSession.sparkContext.defaultParallelism
    return tasks.select("task_id", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).repartitionByRange(n, F.xxhash64("task_id"))


def solve(edges: DataFrame, tasks: DataFrame, provider: str = "onepass", *, bound_options: dict | None = None, search_options: dict | None = None, landmarks: kernel.Landmarks | None = None, bounds_only: bool = False, search_only: bool = False, limit_s: float | None = None, name: str | None = None) -> DataFrame:
    """One row a task: its front, its optima, and every measure. edges: (src, dst, c0..)."""
    arrays = graph_arrays(edges)
    if arrays is None:
        raise ValueError("the network is too large for the kernel; use engine='superstep'")
    sc = edges.sparkSession.sparkContext
    shared = _Shared(edges.sparkSession, arrays)
    table = sc.broadcast(landmarks) if landmarks is not None else None
    bound_options, search_options = dict(bound_options or {}), dict(search_options or {})
    label = name or provider

    def run(batches):
        for pdf in batches:
            rows = []
            for task, s, t in zip(pdf["task_id"].tolist(), pdf["src"].tolist(), pdf["dst"].tolist(), strict=True):
                g = shared.graph
                if table is not None:
                    bound_options["table"] = table.value
                if s not in g.out or t not in g.out:
                    rows.append((task, s, t, label, 0, 0, 0, 0, 0, 0.0, 0.0, False, [{"cost": [0] * g.d, "path": [s]}] if s == t else [], []))
                    continue
                a = time.perf_counter()
                b = kernel.PROVIDERS[provider](g, s, t, **bound_options)
                m = time.perf_counter()
                f = kernel.Found([], set()) if bounds_only else kernel.label_search(g, s, t, b, limit_s=limit_s, **search_options)
                z = time.perf_counter()
                best = [{"criterion": i, "cost": list(x[0]), "path": x[1]} for i, x in enumerate(b.best) if x]
                front = [{"cost": list(c), "path": p} for c, p in f.front]
                rows.append((task, s, t, label, len(b.visited), len(f.visited), len(b.visited | f.visited), f.assembled, f.rejected, (m - a + b.reused_s) * 1e3, (z - m) * 1e3, f.timed_out, front, best))
            yield pd.DataFrame(rows, columns=[c.strip().split()[0] for c in RESULT.split(", ")])

    return _spread(tasks).mapInPandas(run, RESULT)


def bound_rows(edges: DataFrame, tasks: DataFrame, provider: str, landmarks: kernel.Landmarks | None = None, **options) -> DataFrame:
    """(task_id, node, lb) of a provider, from the kernel."""
    sc = edges.sparkSession.sparkContext
    arrays = graph_arrays(edges)
    if arrays is None:
        raise ValueError("the network is too large for the kernel; use the sweeps")
    shared = _Shared(edges.sparkSession, arrays)
    table = sc.broadcast(landmarks) if landmarks is not None else None

    def run(batches):
        for batch in batches:
            for task, s, t in zip(*(batch.column(c).to_pylist() for c in ("task_id", "src", "dst")), strict=True):
                more = {"table": table.value} if table is not None else {}
                b = kernel.PROVIDERS[provider](shared.graph, s, t, **options, **more)
                if b.lb:
                    node, lb = b.lb.table() if isinstance(b.lb, arrays_.Bound) else (np.array(list(b.lb), np.int64), np.array(list(b.lb.values()), np.int64))
                    for k in range(0, len(node), 1 << 16):
                        part = np.ascontiguousarray(lb[k : k + (1 << 16)], np.int64)
                        offsets = pa.array(np.arange(len(part) + 1, dtype=np.int32) * part.shape[1])
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), task)), pa.array(node[k : k + (1 << 16)]), pa.ListArray.from_arrays(offsets, pa.array(part.reshape(-1)))], ["task_id", "node", "lb"])

    return _spread(tasks).mapInArrow(run, "task_id long, node long, lb array<long>")


def single_source_counts(edges: DataFrame, tasks: DataFrame) -> DataFrame:
    """(task_id, nodes, front_rows, paths_assembled, front_size): the search that ends with a front at every node, once for all tasks of a source."""
    shared = _Shared(edges.sparkSession, graph_arrays(edges))

    def run(batches):
        last = None
        for pdf in batches:
            rows = []
            for task, s, t in zip(pdf["task_id"].tolist(), pdf["src"].tolist(), pdf["dst"].tolist(), strict=True):
                if last is None or last[0] != s:
                    g, a = shared.graph, time.perf_counter()
                    if settled.order_of(g) is None:
                        f = kernel.label_search(g, s, t, kernel.Bounds(None), single_source=True, check="off")
                        nodes, made, size = len(f.fronts), f.assembled, {n: len(x) for n, x in f.fronts.items()}
                        every, of = sum(size.values()), lambda n, size=size: size.get(n, 0)
                    else:
                        f = settled.search(g, s, None)
                        nodes, made, every, of = len(f.visited), f.assembled, int(f.rows.sum()), f.size
                    last = s, nodes, every, made, of, (time.perf_counter() - a) * 1e3
                _, nodes, every, made, of, took = last
                rows.append((task, nodes, every, made, of(t), took))
            yield pd.DataFrame(rows, columns=["task_id", "nodes", "front_rows", "paths_assembled", "front_size", "search_ms"])

    ends = tasks.select("task_id", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    return ends.repartition(edges.sparkSession.sparkContext.defaultParallelism, "src").sortWithinPartitions("src").mapInPandas(run, "task_id long, nodes long, front_rows long, paths_assembled long, front_size long, search_ms double")


def build_landmarks(edges: DataFrame, picks: list[int], combine: str = "max") -> kernel.Landmarks:
    """Full searches from and to every landmark, one Spark task each; 2 * k * d values a node come back, within the kernel's limit."""
    spark = edges.sparkSession
    arrays = graph_arrays(edges)
    if arrays is None:
        raise ValueError("the network is too large for landmark arrays; use landmark_table")
    shared = _Shared(spark, arrays)
    nodes, d = shared.arrays.value.nodes, arrays[2].shape[1]

    def run(batches):
        for pdf in batches:
            for r, toward in zip(pdf["lm"].tolist(), pdf["toward"].tolist(), strict=True):
                yield pd.DataFrame({"lm": [r], "toward": [toward], "costs": [kernel.costs_of(shared.graph, not toward, r).astype(np.int64).tobytes()]})

    plan = spark.createDataFrame([(r, w) for r in picks for w in (True, False)], "lm long, toward boolean").repartition(2 * len(picks))
    rows = {(r["lm"], r["toward"]): arrays_.narrow(np.frombuffer(r["costs"], np.int64).reshape(len(nodes), d)) for r in plan.mapInPandas(run, "lm long, toward boolean, costs binary").toLocalIterator()}
    return kernel.Landmarks(kernel.Places(nodes), np.stack([rows[r, True] for r in picks]), np.stack([rows[r, False] for r in picks]), combine)


#: Nodes whose landmark bounds are made and sent together.
PART = 1 << 14


def landmark_parts(spark, graph: Callable[[int], kernel.Graph], lines: dict[int, tuple[list[int], int]], ends: list[int]) -> DataFrame:
    """(line, end, first, size, lb, seconds): what landmarks give for all nodes towards every end, `size` nodes from `first` on a row; lb is (criteria, nodes).

    lines: landmarks and number of criteria by line; graph: the network of a line, asked for in the workers. A task searches
    from one landmark and deals its costs out by parts of the nodes, so neither the driver nor a task holds those of all landmarks.
    """
    n, size = 4 * spark.sparkContext.defaultParallelism, PART

    def search(batches):
        for pdf in batches:
            for line, r in zip(pdf["line"].tolist(), pdf["lm"].tolist(), strict=True):
                g = graph(line)
                costs = arrays_.narrow(np.stack([kernel.costs_of(g, forward, r).T for forward in (False, True)]))
                at = np.array([g.place(t) for t in ends])
                of_ends = np.where(at >= 0, costs[:, :, at], costs.dtype.type(-1)).tobytes()
                for k in range(0, len(g.nodes), size):
                    yield pd.DataFrame({"line": [line], "first": [k], "of_ends": [of_ends], "costs": [costs[:, :, k : k + size].tobytes()]})

    def bounds(batches):
        made, lb, seconds = None, None, None

        def rows():
            return pd.DataFrame({"line": made[0], "end": ends, "first": made[1], "size": lb.shape[2], "lb": [arrays_.narrow(x).tobytes() for x in lb], "seconds": seconds})

        for pdf in batches:
            for line, first, of_ends, costs in zip(pdf["line"].tolist(), pdf["first"].tolist(), pdf["of_ends"], pdf["costs"], strict=True):
                d = lines[line][1]
                kind = f"i{len(of_ends) // (2 * d * len(ends))}"
                (to, away), (to_end, away_end) = (np.frombuffer(x, kind).reshape(2, d, -1) for x in (costs, of_ends))
                if made != (line, first):
                    if made:
                        yield rows()
                    made, lb, seconds = (line, first), np.zeros((len(ends), *to.shape), kind), [0.0] * len(ends)
                lb = lb.astype(kind) if to.itemsize > lb.itemsize else lb
                for j in range(len(ends)):
                    began = time.perf_counter()
                    kernel.raise_by(lb[j], to, away, to_end[:, j, None], away_end[:, j, None])
                    seconds[j] += time.perf_counter() - began
        if made:
            yield rows()

    every = [(i, r) for i, (picks, _) in lines.items() for r in (picks if ends else ())]
    plan = spark.createDataFrame(every, "line int, lm long").repartition(max(1, len(every)))
    costs = plan.mapInPandas(search, "line int, first int, of_ends binary, costs binary").repartition(n, "line", "first").sortWithinPartitions("line", "first")
    return costs.mapInPandas(bounds, "line int, end long, first int, size int, lb binary, seconds double")


class Gathered:
    """The landmark bounds of one line towards one end, put together from their parts."""

    def __init__(self, line: int, end: int):
        self.key, self.lb, self.seconds = (line, end), None, 0.0

    def add(self, g: kernel.Graph, first: int, size: int, lb: bytes, seconds: float) -> None:
        began = time.perf_counter()
        lb = np.frombuffer(lb, f"i{len(lb) // (g.d * size)}").reshape(g.d, size)
        if self.lb is None:
            self.lb = np.zeros((g.d, len(g.nodes)), lb.dtype)
        elif lb.itemsize > self.lb.itemsize:
            self.lb = self.lb.astype(lb.dtype)
        self.lb[:, first : first + size] = lb
        self.seconds += seconds + time.perf_counter() - began

    def bounds(self, g: kernel.Graph) -> kernel.Bounds:
        """Their time counts for every task with that end."""
        reused = self.seconds
        if isinstance(self.lb, np.ndarray):
            began = time.perf_counter()
            self.lb = kernel.everywhere(g, self.lb)
            self.seconds += time.perf_counter() - began
        return kernel.Bounds(self.lb, reused_s=reused)


def grid_landmarks(k: int, width: int, count: int) -> list[int]:
    """k = m*m junctions spread evenly over a grid of the given width: the middle of each of m by m cells."""
    m = math.isqrt(k)
    if m * m != k:
        raise ValueError("k must be a square")
    height = -(-count // width)
    at = lambda i, n: min(n - 1, (2 * i + 1) * n // (2 * m))
    return sorted({min(count - 1, at(i, height) * width + at(j, width)) for i in range(m) for j in range(m)})


def farthest_landmarks(edges: DataFrame, k: int, first: int) -> list[int]:
    """Farthest-first choice by the sum of all criteria, for networks without coordinates."""
    src, dst, cost = graph_arrays(edges)
    g = kernel.Graph(src, dst, cost.sum(1, keepdims=True))
    picks, least = [first], {}
    while len(picks) < min(k, len(g.out)):
        for n, v in kernel.full_costs(g.out, picks[-1], 1).items():
            least[n] = min(least.get(n, v[0]), v[0])
        picks.append(max(least, key=lambda n: (least[n], -n)))
    return picks


def landmark_table(edges: DataFrame, picks: list[int], d: int) -> DataFrame:
    """(node, lm, to_lm, from_lm) by supersteps, for networks of any size."""
    spark = edges.sparkSession
    tasks = spark.createDataFrame([(r, r, r) for r in picks], "task_id long, src long, dst long")
    far = spark.createDataFrame([(r, r, -1) for r in picks], "task_id long, src long, dst long")
    to = sweep.sweep(edges, far.select("task_id", F.lit(-1).cast("long").alias("src"), F.col("src").alias("dst")), d).lb.select(F.col("task_id").alias("lm"), "node", F.col("lb").alias("to_lm"))
    away = sweep.sweep(edges, tasks.select("task_id", "src", F.lit(-1).cast("long").alias("dst")), d, backward=False).lb.select(F.col("task_id").alias("lm"), "node", F.col("lb").alias("from_lm"))
    return to.join(away, ["lm", "node"], "full")


def landmark_bounds(table: DataFrame, tasks: DataFrame, d: int) -> DataFrame:
    """(task_id, node, lb) from a landmark table: max over landmarks of both triangle inequalities, never below 0."""
    at = table.join(F.broadcast(tasks.select("task_id", F.col("dst").alias("node"))), "node").select("task_id", "lm", F.col("to_lm").alias("t_to"), F.col("from_lm").alias("t_from"))
    both = table.join(F.broadcast(at), "lm")
    per = [F.greatest(F.lit(0), F.coalesce(F.max(F.col("to_lm")[i] - F.col("t_to")[i]), F.lit(0)), F.coalesce(F.max(F.col("t_from")[i] - F.col("from_lm")[i]), F.lit(0))).cast("long") for i in range(d)]
    return both.groupBy("task_id", "node").agg(F.array(*per).alias("lb"))


def landmark_violations(bounds: DataFrame, exact: DataFrame) -> DataFrame:
    """Nodes whose bound exceeds the exact cost, as after a fall of some edge costs: (task_id, node, lb, cost)."""
    both = bounds.join(exact.select("task_id", "node", F.col("lb").alias("cost")), ["task_id", "node"])
    return both.where(F.exists(F.zip_with("lb", "cost", lambda x, y: x > y), lambda z: z))


def combined_bounds(*parts: DataFrame) -> DataFrame:
    """Component-wise maximum of valid bounds; nodes that some provider left out stay out."""
    out = parts[0]
    for p in parts[1:]:
        out = out.join(p.withColumnRenamed("lb", "lb2"), ["task_id", "node"]).select("task_id", "node", F.zip_with("lb", "lb2", lambda x, y: F.greatest(x, y)).alias("lb"))
    return out


def manhattan_bounds(nodes: DataFrame, tasks: DataFrame, least_edge: int) -> DataFrame:
    """Straight-line bound on a grid: cells apart times the least cost of an edge."""
    t = tasks.join(nodes, F.col("dst") == F.col("node")).select("task_id", F.col("x").alias("tx"), F.col("y").alias("ty"))
    return nodes.join(F.broadcast(t)).select("task_id", "node", F.array(((F.abs(F.col("x") - F.col("tx")) + F.abs(F.col("y") - F.col("ty"))) * least_edge).cast("long")).alias("lb"))


def path_front(edges: DataFrame, tasks: DataFrame, criteria: list[str], bounds: str = "onepass", engine: str = "auto", **options) -> DataFrame:
    """(task_id, cost, path, n_hops): every non-dominated path of every task. edges carry named cost columns.

    engine='auto' searches in memory up to EDGE_LIMIT edges and by supersteps above; what supersteps lack is an error there.
    """
    part = project(edges, criteria)
    d = len(criteria)
    if engine == "auto":
        engine = "kernel" if part.count() <= kernel.EDGE_LIMIT else "superstep"
    if engine == "kernel":
        got = solve(part, tasks, bounds, bound_options=options.get("bound_options"), search_options=options.get("search_options"), landmarks=options.get("landmarks"))
        rows = got.select("task_id", F.explode("front").alias("f")).select("task_id", "f.cost", "f.path")
    else:
        if bounds not in ("none", "onepass", "twosided", "multi"):
            raise ValueError(f"bounds {bounds!r} are computed in memory only, for at most {kernel.EDGE_LIMIT} edges; supersteps have none, multi, onepass and twosided")
        known = set(inspect.signature(labels.path_fronts).parameters)
        if strange := sorted({*options.get("search_options", {})} - known) + sorted({"bound_options", "landmarks"} & {*options}):
            raise ValueError(f"supersteps do not have the options {strange}; the front is the same without them")
        lb = anchors = None
        if bounds == "twosided":
            r = sweep.twosided_bounds(part, tasks, d)
        elif bounds != "none":
            r = sweep.sweep(part, tasks, d, prune=bounds == "onepass")
        if bounds != "none":
            lb, anchors = r.lb, r.anchors
        found, _ = labels.path_fronts(part, tasks, d, lb, anchors, **options.get("search_options", {}))
        rows = found.select("task_id", F.array(*(f"c{i}" for i in range(d))).alias("cost"), "path")
    return rows.withColumn("n_hops", (F.size("path") - 1).cast("int"))


def solution_graph(fronts: DataFrame) -> DataFrame:
    """(task_id, src, dst): the edges of all front paths."""
    steps = F.transform(F.sequence(F.lit(0), F.size("path") - 2), lambda i: F.struct(F.get("path", i).alias("src"), F.get("path", i + 1).alias("dst")))
    return fronts.where(F.size("path") > 1).select("task_id", F.explode(steps).alias("e")).select("task_id", "e.src", "e.dst").distinct()


def keep(df: DataFrame, label: str) -> DataFrame:
    return materialise(df, label)
