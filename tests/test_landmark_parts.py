"""Landmark bounds of the workloads: made by parts of the nodes, with the values of the whole table, which is nowhere whole."""

import pickle

import numpy as np
import pytest
from pyspark import SparkContext

from routefront import workloads as W
from routefront.plans import batch
from routefront.plans import kernel as K
from routefront.sources import networks as N
from routefront.sources import tasks as T

GRID = (13, 150)  # of sf0.001


def test_no_broadcast_grows_with_the_landmarks(spark, tiny, monkeypatch):
    sent, real = [], SparkContext.broadcast
    monkeypatch.setattr(SparkContext, "broadcast", lambda self, value: sent.append(len(pickle.dumps(value))) or real(self, value))
    edges, tasks, by_landmarks = N.grid_road(spark, tiny), T.mini(spark, tiny), {}
    network = W.share(edges)
    for k in (1, 49):
        sent.clear()
        rows = W.run(edges, tasks, [W.Config("tel", "landmark", landmarks=k), W.Config("tel", "none", "label_search", search={"check": "basic"})], grid=GRID, network=network).collect()
        sizes = {name: {r["task_id"]: r["front_size"] for r in rows if r["provider"] == name} for name in (f"landmark{k}", "label_search")}
        assert len(sizes["label_search"]) == 20 and sizes[f"landmark{k}"] == sizes["label_search"]
        by_landmarks[k] = sum(sent)
    assert by_landmarks[49] == by_landmarks[1]


@pytest.mark.parametrize("edges, unit", [(500, 1), (6000, 1), (500, 1 << 33)])
def test_parts_have_the_bounds_of_the_whole_table(spark, monkeypatch, edges, unit):
    monkeypatch.setattr(batch, "PART", 64)
    rng = np.random.default_rng(edges)
    src, dst = rng.integers(0, 300, (2, edges))
    g = K.Graph(np.append(src, 400), np.append(dst, 401), np.append(rng.integers(1, 50, (edges, 3)), [[1, 1, 1]], 0) * unit)  # 400 and 401 apart from the others
    picks, ends = [3, 40, 299, 400], [7, 200, 401, 500]
    table = K.Landmarks(K.Places(g.nodes), *(np.stack([K.costs_of(g, forward, r).astype(np.int64) for r in picks]) for forward in (False, True)))
    found = {end: batch.Gathered(0, end) for end in ends}
    for r in batch.landmark_parts(spark, lambda line: g, {0: (picks, 3)}, ends).collect():
        found[r["end"]].add(g, r["first"], r["size"], bytes(r["lb"]), r["seconds"])
    for end in ends[:3]:
        assert (found[end].lb == table.toward(end).T).all()
        assert dict(found[end].bounds(g).lb.items()) == dict(K.landmark(g, 7, end, table).lb.items())
    assert not found[500].lb.any()  # no such node, nothing is known


def test_ends_that_no_edge_touches(spark, tiny):
    tasks = spark.createDataFrame([(1, 0, 9999), (2, 9999, 5), (3, 9999, 9999), (4, 5, 70)], "task_id long, src long, dst long")
    configs = [W.Config("tel", "onepass"), W.Config("tel", "landmark", landmarks=4), W.Config("tel", "none", "label_search", search={"check": "basic"})]
    rows = W.run(N.grid_road(spark, tiny), tasks, configs, grid=GRID).collect()
    sizes = [{r["task_id"]: r["front_size"] for r in rows if r["provider"] == c.name} for c in configs]
    assert sizes[0] == sizes[1] == sizes[2]
    assert [sizes[0][k] for k in (1, 2, 3)] == [0, 0, 1] and sizes[0][4] > 0
