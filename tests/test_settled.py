"""Front sizes by buckets of labels against label correction, node by node, and grids whose fronts that could not hold."""

import random

import numpy as np
import pytest

from routefront import workloads as W
from routefront.functions import criteria as C
from routefront.plans import batch, settled
from routefront.plans import kernel as K
from routefront.sources import networks as N
from routefront.sources import tasks as T


@pytest.mark.parametrize("seed", range(60))
def test_sizes_equal_those_of_label_correction(seed, monkeypatch):
    r = random.Random(seed)
    n = r.randint(4, 12)
    rows = [(*r.sample(range(0, n * 3, 3), 2), r.choice([1, 2, 2, 3, 5]), r.choice([0, 0, 1, 2, 3, 5])) for _ in range(r.randint(n, 4 * n))]
    a = np.array([(x, y, d, c) for x, y, c, d in rows] if seed % 2 else rows, np.int64)
    monkeypatch.setattr(K, "STEPWISE", -1 if seed % 3 else 4096)
    g = K.Graph(a[:, 0], a[:, 1], a[:, 2:])
    s, t = int(g.nodes[0]), int(g.nodes[-1])
    want = K.label_search(g, s, t, K.Bounds(None), single_source=True, check="off").fronts
    f = settled.search(g, s, None)
    assert {m: f.size(m) for m in f.visited} == {m: len(c) for m, c in want.items()}
    for p in ("none", "pair", "onepass", "twosided", "multi"):
        b = K.PROVIDERS[p](g, s, t)
        assert settled.search(g, s, t, b.lb, b.anchors).size(t) == len(want.get(t, ()))


def test_all_fronts_of_a_block(monkeypatch):
    """Half a million labels at 8,100 nodes; a node keeps one number."""
    w = 90
    i = np.arange(w * w)
    right, down = i[i % w < w - 1], i[i < w * (w - 1)]
    src, dst = np.concatenate([right, right + 1, down, down + w]), np.concatenate([right + 1, right, down + w, down])
    g = K.Graph(src, dst, np.stack([(src * 7 + dst * 3) % 50 + 20, (src * 5 + dst * 11) % 60], 1))
    f = settled.search(g, w * w // 2 + w // 2, None, limit_s=30)
    assert not f.timed_out and len(f.visited) == w * w and int(f.rows.sum()) > 100_000


def test_a_source_is_searched_once(spark, tiny):
    """All tasks of a source have its counts; the workload's two ways end with the same fronts."""
    e = N.project(N.city(spark, tiny), C.columns("te"))
    rows = batch.single_source_counts(e, T.mini(spark, tiny)).join(T.mini(spark, tiny), "task_id").collect()
    assert len(rows) == 20 and len({(r["src"], r["nodes"], r["front_rows"], r["paths_assembled"], r["search_ms"]) for r in rows}) == 5
    both = {r["provider"]: r for r in W.w01_single_source_vs_target(spark, tiny).collect()}
    assert both["label_search"]["front_size"] == both["single_source"]["front_size"] and both["single_source"]["tasks"] == both["label_search"]["tasks"] == 702


def test_landmark_bounds_of_an_end_are_made_once(monkeypatch):
    a = np.array([(i, i + 1, 1 + i % 3, 2) for i in range(9)] + [(i + 1, i, 2, 1 + i % 2) for i in range(9)], np.int64)
    g = K.Graph(a[:, 0], a[:, 1], a[:, 2:])
    table = K.Landmarks(K.Places(g.nodes), np.stack([K.costs_of(g, False, 4)]), np.stack([K.costs_of(g, True, 4)]))
    made, toward = [], K.Landmarks.toward
    monkeypatch.setattr(K.Landmarks, "toward", lambda self, t: made.append(t) or toward(self, t))
    found = [K.landmark(g, s, t, table) for s, t in ((0, 8), (1, 8), (2, 8), (0, 7))]
    assert made == [8, 7] and found[0].lb == found[2].lb != found[3].lb and found[1].reused_s > 0
