"""Full searches by supersteps of whole blocks of nodes: a job a crossing of blocks, where `sweep` takes a job a hop.

Nodes are cut into blocks of like many edges by their ids. A superstep searches each block to its end from the entries that
came in, and hands on what its border nodes have gained. Entries are those of `sweep`, in flat columns: v{i} the least value
of criterion i, t{i} the total of its walk, x{i} the walk's first node, y{i}_{j} its cost vector.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrays
from .loop import Trace, materialise, run_supersteps

#: Edges of a block, about.
BLOCK_EDGES = 250_000


def _fields(d: int) -> list[str]:
    return [x for i in range(d) for x in (f"v{i}", f"t{i}", f"x{i}", *(f"y{i}_{j}" for j in range(d)))]


def bits_of(edges: DataFrame, d: int) -> tuple[int | None, int]:
    """Bits of a walk's total in an entry of 62 bits (None: entries do not fit, or costs are null or negative), and the number of edges."""
    costs = [F.col(f"c{i}") for i in range(d)]
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.max(sum(costs, F.lit(0))).alias("total"), F.max(F.greatest(F.lit(0), *costs)).alias("most"), F.min(F.least(F.lit(0), *costs)).alias("least"), F.countDistinct("from_").alias("nodes"), F.count(F.when(sum(costs, F.lit(0)).isNull(), 1)).alias("null")).first()
    bits = (int(r["total"] or 0) * (r["nodes"] + 1)).bit_length()
    return None if r["least"] is None or r["least"] < 0 or r["null"] or bits + (int(r["most"] or 0) * (r["nodes"] + 1)).bit_length() > 62 else bits, r["n"]


def _local(tail: np.ndarray, head: np.ndarray, cost: np.ndarray, extra: np.ndarray) -> arrays.Graph:
    """The edges within a block, and nodes that have none."""
    g = object.__new__(arrays.Graph)
    g.nodes = np.unique(np.concatenate([tail, head, extra]))
    at = np.searchsorted(g.nodes, tail)
    order = np.argsort(at, kind="stable")
    g.tail, g.head = at[order], np.searchsorted(g.nodes, head[order])
    g.begin = np.searchsorted(g.tail, np.arange(len(g.nodes) + 1))
    g.cost = [np.ascontiguousarray(cost[order, i]) for i in range(cost.shape[1])]
    g.by_head, g.into_begin = np.zeros(0, np.int64), np.zeros(1, np.int64)
    g._rest()
    return g


def _search(g: arrays.Graph, rows: pd.DataFrame, i: int, d: int, bits: int) -> tuple[np.ndarray, ...]:
    """Criterion i of one task in a block, to its end: entry, first node and cost vector of every node, and which have gained."""
    place = np.searchsorted(g.nodes, rows["node"].to_numpy())
    key, came = (rows[f"v{i}"].to_numpy() << bits) | rows[f"t{i}"].to_numpy(), rows["open"].to_numpy()
    order = np.lexsort((rows[f"x{i}"].to_numpy(), key, place))
    first = order[np.append(True, place[order][1:] != place[order][:-1])]
    old = np.full(len(g.nodes), arrays.FAR)
    np.minimum.at(old, place[~came], key[~came])
    nxt, vec = np.full(len(g.nodes), -1), np.zeros((len(g.nodes), d), np.int64)
    nxt[place[first]], vec[place[first]] = rows[f"x{i}"].to_numpy()[first], rows[[f"y{i}_{j}" for j in range(d)]].to_numpy()[first]
    w = arrays.Wave(g, True, 0, [i])
    w.key[0] = arrays.FAR
    w.key[0, place[first]] = key[first]
    w.pool = np.flatnonzero(w.key[0] < old)
    w.pooled[:] = False
    w.pooled[w.pool] = True
    w.run()
    via = w.via[0]
    new = np.flatnonzero(via >= 0)
    new = new[np.argsort(w.key[0, new], kind="stable")]  # a walk's rest has the smaller entry
    if len(new):
        nxt[new] = g.nodes[g.tail[via[new]]]
        for j in range(d):
            y, add = vec[:, j].tolist(), g.cost[j][via[new]].tolist()
            for n, m, c in zip(new.tolist(), g.tail[via[new]].tolist(), add, strict=True):
                y[n] = y[m] + c
            vec[:, j] = y
    return w.key[0], nxt, vec, w.key[0] < old


def full_sweep(graph: DataFrame, seed: DataFrame, d: int, bits: int, count: int, *, block_edges: int | None = None, most: int = 10_000, limit_s: float | None = None) -> tuple[DataFrame, Trace]:
    """State (task_id, node, w0.., open) of searches without pruning. graph: (from_, to_, c0..); seed: a state as `sweep` makes it."""
    n = max(1, -(-count // (block_edges or BLOCK_EDGES)))
    cuts = sorted({int(x) for x in graph.approxQuantile("from_", [k / n for k in range(1, n)], 0.2 / n)}) if n > 1 else []
    block = lambda c: F.size(F.filter(F.array(*(F.lit(x).cast("long") for x in cuts)), lambda x: x <= F.col(c))).cast("int") if cuts else F.lit(0)
    costs = [f"c{i}" for i in range(d)]
    graph = materialise(graph.select(block("from_").alias("block"), "from_", block("to_").alias("to_block"), "to_", *costs), "edges")
    flat = [F.col(f"w{i}.{a}").alias(f"{b}{i}") for i in range(d) for a, b in (("value", "v"), ("total", "t"), ("next", "x"))] + [F.col(f"w{i}.vec")[j].alias(f"y{i}_{j}") for i in range(d) for j in range(d)]
    state = seed.select("task_id", "node", block("node").alias("block"), "open", *flat)
    names = ["task_id", "node", "block", "open", *_fields(d)]
    schema = ", ".join(f"{x} {'int' if x == 'block' else 'boolean' if x == 'open' else 'long'}" for x in names)

    def run(rows: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        if not len(rows) or not rows["open"].any():
            return rows[names]
        own = int(rows["block"].iloc[0])
        inside = (edges["to_block"] == own).to_numpy()
        near, far = edges[inside], edges[~inside]
        g = _local(near["from_"].to_numpy(), near["to_"].to_numpy(), near[costs].to_numpy(), np.unique(np.concatenate([rows["node"].to_numpy(), far["from_"].to_numpy()])))
        g.bits = bits
        tail, cost, total = np.searchsorted(g.nodes, far["from_"].to_numpy()), far[costs].to_numpy(), far[costs].to_numpy().sum(1)
        out = []
        for task, part in rows.groupby("task_id"):
            found = [_search(g, part, i, d, bits) for i in range(d)]
            known, gained = found[0][0] < arrays.FAR, np.any([f[3] for f in found], 0)
            go = np.flatnonzero(gained[tail])
            mine, theirs = {"task_id": task, "node": g.nodes[known], "block": own, "open": False}, {"task_id": task, "node": far["to_"].to_numpy()[go], "block": far["to_block"].to_numpy()[go], "open": True}
            for i, (key, nxt, vec, _) in enumerate(found):
                value, sum_ = key >> bits, key & ((1 << bits) - 1)
                mine |= {f"v{i}": value[known], f"t{i}": sum_[known], f"x{i}": nxt[known], **{f"y{i}_{j}": vec[known, j] for j in range(d)}}
                theirs |= {f"v{i}": value[tail[go]] + cost[go, i], f"t{i}": sum_[tail[go]] + total[go], f"x{i}": g.nodes[tail[go]], **{f"y{i}_{j}": vec[tail[go], j] + cost[go, j] for j in range(d)}}
            out += [pd.DataFrame(mine)[names], pd.DataFrame(theirs)[names]]
        return pd.concat(out)

    def step(s: DataFrame, k: int) -> DataFrame:
        return s.groupBy("block").cogroup(graph.groupBy("block")).applyInPandas(run, schema)

    done, trace = run_supersteps(state, step, lambda s: s.where("open").count(), most=most, limit_s=limit_s, label="blocks")
    walk = lambda i: F.struct(F.col(f"v{i}").alias("value"), F.col(f"t{i}").alias("total"), F.col(f"x{i}").alias("next"), F.array(*(F.col(f"y{i}_{j}") for j in range(d))).alias("vec"))
    if trace.timed_out:  # entries that came in are not merged yet
        done = done.groupBy("task_id", "node").agg(*(F.min(walk(i)).alias(f"w{i}") for i in range(d)), F.max("open").alias("open"))
        return done, trace
    return done.select("task_id", "node", *(walk(i).alias(f"w{i}") for i in range(d)), "open"), trace
