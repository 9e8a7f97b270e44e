"""Path fronts of three criteria by label setting in lexicographic order of cost plus bound.

With consistent bounds the first criterion of the labels that leave the queue never falls, neither in all nor, less the
bound, at one node. So a label is dominated exactly if one that left before it is no worse in the other two criteria: a
node keeps those as a staircase (ascending in one, descending in the other) and a check is one binary search. Labels with
equal cost vectors are one label; the front has one path a vector.
"""

from __future__ import annotations

import time
from bisect import bisect_right
from heapq import heappop, heappush

from .arrays import Graph


class Staircase:
    """Non-dominated pairs, the first ascending, the second descending."""

    __slots__ = ("x", "y")

    def __init__(self):
        self.x, self.y = [], []

    def beats(self, a: int, b: int) -> bool:
        i = bisect_right(self.x, a)
        return i > 0 and self.y[i - 1] <= b

    def add(self, a: int, b: int) -> None:
        x, y = self.x, self.y
        i = bisect_right(x, a)
        if i and x[i - 1] == a:
            i -= 1
        j = i
        while j < len(y) and y[j] >= b:
            j += 1
        x[i:j], y[i:j] = [a], [b]


def search(g: Graph, s: int, t: int, lb, limit_s: float | None = None, anchors=()) -> tuple[list, set[int], int, int, bool]:
    """Front as (cost, path), visited nodes, labels made, labels dropped, whether the limit was hit. lb: consistent bounds by node id; a node without one is left out.

    Where a pruned sweep left a bound that is not consistent, an anchor dominates every label with it, so it never gets here.
    """
    began = time.monotonic()
    if s not in lb:
        return [], {s}, 0, 0, False
    near: dict[int, list] = {}  # edges to nodes with bounds: node, cost vector, its bound
    stairs: dict[int, Staircase] = {}
    goal = Staircase()
    h = lb[s]
    nodes, costs, parent = [s], [(0, 0, 0)], [-1]
    heap = [(*h, 0)]
    front, made, dropped, late = [], 0, 0, False
    seen = {s}
    beaten_by = [tuple(a) for a in anchors]
    while heap:
        f0, f1, f2, k = heappop(heap)
        n = nodes[k]
        g0, g1, g2 = costs[k]
        own = stairs.get(n)
        if own is None:
            own = stairs[n] = Staircase()
        if own.beats(g1, g2) or goal.beats(f1, f2):
            dropped += 1
            continue
        own.add(g1, g2)
        if n == t:
            goal.add(f1, f2)
            front.append(k)
            continue
        if not k & 1023 and limit_s is not None and time.monotonic() - began > limit_s:
            late = True
            break
        out = near.get(n)
        if out is None:
            out = near[n] = [(m, *c, *lb[m]) for m, c in g.out.get(n, ()) if m != s and m in lb]
        for m, c0, c1, c2, h0, h1, h2 in out:
            made += 1
            a0, a1, a2 = g0 + c0, g1 + c1, g2 + c2
            e0, e1, e2 = a0 + h0, a1 + h1, a2 + h2
            if goal.beats(e1, e2):
                dropped += 1
                continue
            there = stairs.get(m)
            if there is not None and there.beats(a1, a2):
                dropped += 1
                continue
            for b in beaten_by:
                if b[0] <= e0 and b[1] <= e1 and b[2] <= e2 and b != (e0, e1, e2):
                    dropped += 1
                    break
            else:
                seen.add(m)
                nodes.append(m)
                costs.append((a0, a1, a2))
                parent.append(k)
                heappush(heap, (e0, e1, e2, len(nodes) - 1))
    found = []
    for k in front:
        path, i = [], k
        while i >= 0:
            path.append(nodes[i])
            i = parent[i]
        found.append((costs[k], path[::-1]))
    return sorted(found), seen, made, dropped, late
