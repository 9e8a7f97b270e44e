"""Full searches by blocks of nodes: the bounds of searches in memory, in far fewer supersteps than there are hops."""

import numpy as np
import pytest

from routefront.plans import batch, blocks, sweep
from routefront.sources import tasks as T


@pytest.mark.parametrize("block_edges", [300, 2000])
def test_blocks_give_full_searches(spark, monkeypatch, block_edges):
    w = 30
    i = np.arange(w * w)
    right, down = i[i % w < w - 1], i[i < w * (w - 1)]
    src, dst = np.concatenate([right, right + 1, down, down + w]), np.concatenate([right + 1, right, down + w, down])
    rows = [(int(a), int(b), int((a * 7 + b * 3) % 50), int((a * 5 + b * 11) % 60 + 1)) for a, b in zip(src, dst) if (a * 31 + b) % 11] + [(5000, 5001, 1, 1)]
    e = spark.createDataFrame(rows, "src long, dst long, c0 long, c1 long")
    t = T.task_list(spark, [(0, w * w // 2), (w * w - 1, 5), (0, 5001)])
    monkeypatch.setattr(blocks, "BLOCK_EDGES", block_edges)
    got = sweep.multi_bounds(e, t, 2)
    order = lambda df: sorted((r["task_id"], r["node"], tuple(r["lb"])) for r in df.collect())
    assert order(got.lb) == order(batch.bound_rows(e, t, "multi"))
    assert got.trace.supersteps < 20  # of up to 58 hops
    best = {(r["task_id"], r["criterion"]): tuple(r["cost"]) for r in got.anchors.collect()}
    want = {(r["task_id"], b["criterion"]): tuple(b["cost"]) for r in batch.solve(e, t, "multi", bounds_only=True).collect() for b in r["best"]}
    assert best == want
    cost = {(a, b): (x, y) for a, b, x, y in rows}
    for r in got.paths(0).collect():
        assert tuple(np.sum([cost[s] for s in zip(r["path"], r["path"][1:])], 0)) == best[r["task_id"], 0]


def test_the_source_is_passed_through(spark):
    """The best way of node 1 leads through the source; it was left out."""
    e = spark.createDataFrame([(1, 0, 1, 1), (0, 2, 1, 1), (1, 2, 9, 9)], "src long, dst long, c0 long, c1 long")
    lb = {r["node"]: tuple(r["lb"]) for r in sweep.multi_bounds(e, T.task_list(spark, [(0, 2)]), 2).lb.collect()}
    assert lb == {2: (0, 0), 0: (1, 1), 1: (2, 2)}
