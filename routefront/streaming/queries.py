"""Streaming queries; each has a batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import criteria as C
from ..plans import batch
from ..sources import networks as N
from ..sources import tasks as T
from . import updates as U

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


_UP = "SELECT event_id % 1000 AS edge_id, ts, event_id, 50 + CAST(floor(value) AS BIGINT) % 101 AS percent FROM events"


@query(f"SELECT edge_id, count(*) AS n, sum(percent)::BIGINT AS total FROM ({_UP}) GROUP BY edge_id")
def stream_updates_batch_equiv(spark, d):
    u = U.updates(U.event_stream(spark, d), 1000)
    return U.run_to_memory(u.groupBy("edge_id").agg(F.count(F.lit(1)).alias("n"), F.sum("percent").alias("total")))


@query("SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def ev_tumbling(spark, d):
    w = U.event_stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return U.run_to_memory(w).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("SELECT start, count(*) AS n FROM (SELECT unnest(CASE WHEN hour(ts) >= 12 THEN [date_trunc('day', ts), date_trunc('day', ts) + INTERVAL 12 HOUR] ELSE [date_trunc('day', ts) - INTERVAL 12 HOUR, date_trunc('day', ts)] END)::TIMESTAMP AS start FROM events) GROUP BY start")
def ev_sliding(spark, d):
    w = U.event_stream(spark, d).groupBy(F.window("ts", "24 hours", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
    return U.run_to_memory(w).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 DAY THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM s GROUP BY user_id, k")
def ev_session(spark, d):
    w = U.event_stream(spark, d).groupBy(F.session_window("ts", "2 days"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return U.run_to_memory(w).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT count(*) AS late FROM (SELECT ts, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) WHERE ts < seen - INTERVAL 10 DAY")
def ev_late_rows(spark, d):
    """Rows that a ten-day watermark would count as late if events came in order of their id (batch twin of the drop)."""
    from pyspark.sql import Window

    w = Window.orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = N.table(spark, d, "events").select("event_id", "ts")
    return e.withColumn("seen", F.max("ts").over(w)).where(F.col("ts") < F.col("seen") - F.expr("INTERVAL 10 DAYS")).agg(F.count(F.lit(1)).alias("late"))


@query(f"SELECT edge_id, max_by(percent, struct_pack(a := ts, b := event_id)) AS percent FROM ({_UP}) GROUP BY edge_id")
def ev_latest_cost(spark, d):
    return U.run_to_memory(U.latest(U.updates(U.event_stream(spark, d), 1000)))


@query("SELECT count(DISTINCT event_id) AS n FROM events")
def ev_dedup(spark, d):
    s = U.event_stream(spark, d)
    twice = s.union(s).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return U.run_to_memory(twice.select("event_id"), "append").agg(F.countDistinct("event_id").alias("n"))


@query("SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON c_custkey = event_id % 100 GROUP BY c_mktsegment")
def ev_stream_static(spark, d):
    c = N.table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    s = U.event_stream(spark, d).withColumn("c_custkey", F.col("event_id") % 100).join(c, "c_custkey").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    return U.run_to_memory(s)


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR")
def ev_stream_stream(spark, d):
    s = U.event_stream(spark, d)
    a = s.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "1 day")
    b = s.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 day")
    j = a.join(b, F.expr("u1 = u2 AND t2 BETWEEN t1 AND t1 + INTERVAL 6 HOURS"))
    return U.run_to_memory(j.select("click", "purchase"), "append")


@query()
def stream_reanswer(spark, d):
    """Fronts of registered tasks after every micro-batch of cost updates."""
    return U.answer_each_batch(spark, d, T.task_list(spark, [(0, 5)]), "te")


@query()
def w14_dynamic_costs(spark, d):
    """After re-pricing: fresh one-pass fronts beside the violations of landmark bounds built on the old costs."""
    edges = batch.keep(U.numbered(N.grid_road(spark, d)), "numbered")
    now = batch.keep(U.reprice(edges, U.latest(U.updates(N.table(spark, d, "events"), edges.count()))), "repriced")
    tasks = T.mini(spark, d)
    n = N.table(spark, d, "customer").count()
    old = N.project(edges, C.columns("te"))
    lm = batch.build_landmarks(old, batch.grid_landmarks(4, N.grid_width(spark, d), n))
    stale = batch.landmark_violations(batch.bound_rows(N.project(now, C.columns("te")), tasks, "landmark", lm), batch.bound_rows(N.project(now, C.columns("te")), tasks, "multi"))
    fresh = batch.path_front(now, tasks, C.columns("te")).groupBy("task_id").agg(F.countDistinct("cost").alias("front_size"))
    return fresh.join(stale.groupBy("task_id").agg(F.count(F.lit(1)).alias("stale_bounds")), "task_id", "left").select("task_id", "front_size", F.coalesce("stale_bounds", F.lit(0)).alias("stale_bounds"))
