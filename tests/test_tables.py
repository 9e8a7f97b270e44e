"""Queries that read the given tables where they did not, and joins that do not grow with the square of a group."""


from routefront import queries as Q
from routefront import surface, workloads
from routefront.functions import criteria as C
from routefront.plans import batch
from routefront.sources import networks as N
from routefront.sources import tasks as T


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_range_band_join_makes_no_pairs(spark, tmp_path):
    rows = [(i % 7 if i % 5 else None, "ab"[i % 2] if i % 11 else None, (i % 9) * 1.1 if i % 13 else None) for i in range(120)]
    spark.createDataFrame(rows, "p_partkey long, p_brand string, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    got = surface.range_band_join(spark, str(tmp_path))
    assert "Join" not in plan(got)
    want = {}
    for k, b, x in rows:
        n = sum(b == c and x <= y <= x + 5 and k != m for m, c, y in rows if None not in (m, c, y)) if None not in (k, b, x) else 0
        if n:
            want[k] = want.get(k, 0) + n
    assert {r["p_partkey"]: r["pairs"] for r in got.collect()} == want


def test_landmark_pick_reads_customers(spark, tiny):
    got = Q.landmark_pick(spark, tiny)
    assert "parquet" in plan(got)
    assert sorted(r["node"] for r in got.collect()) == Q._grid_lm(spark, tiny, 4)


def test_w13_is_on_the_grid(spark, tiny):
    """Bounds of a task on the customers' network: exact at its source, never above the exact costs near it."""
    task = T.local(spark, tiny).orderBy("task_id").limit(1)
    got = {r["node"]: (r["b0"], r["b1"]) for r in workloads.w13_fixture(spark, tiny).collect()}
    exact = {r["node"]: tuple(r["lb"]) for r in batch.bound_rows(N.project(N.grid_road(spark, tiny), C.columns("te")), task, "multi").collect()}
    s, t = task.select("src", "dst").first()
    assert got[s] == exact[s] and got[t] == (0, 0)
    assert set(got) <= set(exact)
