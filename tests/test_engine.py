"""Supersteps against the kernel, front operators against each other, networks, tasks and negative cases."""

import pytest
from pyspark.sql import functions as F

from routefront.functions import criteria as C
from routefront.operators import front as fr
from routefront.plans import batch, labels, sweep
from routefront.sources import networks as N
from routefront.sources import tasks as T


def rows(df):
    return sorted(tuple(tuple(v) if isinstance(v, list) else v for v in r) for r in df.collect())


@pytest.fixture(scope="module")
def small(spark):
    """A 4 by 4 grid with two criteria, some of them zero."""
    e = []
    for y in range(4):
        for x in range(4):
            for dx, dy in ((1, 0), (0, 1), (-1, 0), (0, -1)):
                if 0 <= x + dx < 4 and 0 <= y + dy < 4:
                    a, b = 4 * y + x, 4 * (y + dy) + x + dx
                    e.append((a, b, (a * 7 + b * 3) % 5 + 1, (a * 5 + b * 11) % 6))
    return spark.createDataFrame(e, "src long, dst long, c0 long, c1 long")


def test_supersteps_equal_the_kernel(spark, small):
    tasks = T.task_list(spark, [(0, 15), (5, 5)])
    named = small.withColumnsRenamed({"c0": "c_time", "c1": "c_energy"})
    for bounds in ("onepass", "twosided"):
        a = batch.path_front(named, tasks, ["c_time", "c_energy"], bounds, "superstep").select("task_id", "cost", "path")
        b = batch.path_front(named, tasks, ["c_time", "c_energy"], bounds, "kernel").select("task_id", "cost", "path")
        assert rows(a) == rows(b)


def test_sweep_without_pruning_is_multi(spark, small):
    tasks = T.task_list(spark, [(0, 15)])
    a = sweep.sweep(small, tasks, 2, expand_end=True)
    assert rows(a.lb) == rows(batch.bound_rows(small, tasks, "multi"))
    path = a.paths(0).first()["path"]
    assert path[0] == 0 and path[-1] == 15


def test_loop_flags_a_cut_run(spark, small):
    tasks = T.task_list(spark, [(0, 15)])
    _, trace = labels.path_fronts(small, tasks, 2, most=2)
    assert trace.timed_out and trace.supersteps == 2


@pytest.mark.parametrize("d", [2, 3])
def test_front_ways_agree(spark, d):
    import random

    r = random.Random(d)
    names = ["a", "b", "c"][:d]
    df = spark.createDataFrame([(i % 3, *(r.randint(0, 6) for _ in range(d))) for i in range(120)], "g int, " + ", ".join(f"{n} long" for n in names))
    want = rows(fr.front(df, names, ["g"], "anti"))
    assert rows(fr.front(df, names, ["g"])) == want
    if d == 2:
        assert rows(fr.front(df, names, ["g"], "sorted2")) == want
    assert len(rows(fr.front(df, names, ["g"], ties="one"))) == len(set(want))


def test_front_of_nothing_and_of_nulls(spark):
    df = spark.createDataFrame([(1, None), (None, 2)], "a long, b long")
    assert fr.front(df, ["a", "b"]).count() == 0
    assert fr.front(df.limit(0), ["a", "b"]).count() == 0
    with pytest.raises(ValueError):
        fr.front(df, ["a", "b"], how="magic")


def test_grid_and_tasks(spark, tiny):
    e = N.grid_road(spark, tiny)
    assert e.count() == 466 and e.select(F.min("c_time")).first()[0] >= 27
    assert T.local(spark, tiny).count() == 702 and T.wide(spark, tiny).count() == 90
    f = batch.path_front(e, T.task_list(spark, [(0, 50), (0, 140)]), C.columns("td"))
    got = f.where("task_id = 1").select("cost").distinct()
    assert rows(got) == [((991, 2417),), ((1010, 1914),)]
    assert f.where("task_id = 2").select("cost").distinct().count() == 4


@pytest.mark.parametrize("bad", [(1, 2, -1, 1), (1, 2, 0, 0), (1, 2, None, 1)])
def test_bad_edges_are_named(spark, bad):
    with pytest.raises(ValueError, match="edges have"):
        N.check(spark.createDataFrame([bad], "src long, dst long, a long, b long"), ["a", "b"])


def test_two_sided_visits_least_on_average(spark, tiny):
    e = N.project(N.grid_road(spark, tiny), C.columns("te"))
    t = T.local(spark, tiny)
    v = {p: batch.solve(e, t, p, bounds_only=True).agg(F.avg("visited_bounds")).first()[0] for p in ("multi", "onepass", "twosided")}
    assert v["twosided"] < v["onepass"] < v["multi"]
