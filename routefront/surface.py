"""The relational surface around networks and fronts: joins, windows, grouping sets, as-of and interval joins, functions."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle
from .functions import criteria as C
from .functions import dominance as D
from .plans import batch
from .plans.loop import shared_dir
from .sources import networks as N
from .sources import tasks as T

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


G, TR, FL = f"WITH {oracle.GRID}", f"WITH {oracle.TRADE}", f"WITH {oracle.FLOW}"


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return N.table(spark, d, name)


@query("SELECT 'customer' AS name, count(*) AS n FROM customer UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT 'lineitem', count(*) FROM lineitem")
def src_network_tables(spark, d):
    out = None
    for n in ("customer", "nation", "lineitem"):
        one = t(spark, d, n).agg(F.count(F.lit(1)).alias("n")).select(F.lit(n).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query(f"{G} SELECT * FROM edges")
def edge_csv_roundtrip(spark, d):
    path = f"{shared_dir(spark).rstrip('/')}/edges-{uuid.uuid4().hex}"
    N.grid_road(spark, d).write.option("header", True).csv(path)
    return N.read_edges(spark, path)


@query(f"{G} SELECT *, src % 4 AS part FROM edges")
def sink_roundtrip(spark, d):
    path = f"{shared_dir(spark).rstrip('/')}/edges-{uuid.uuid4().hex}"
    N.grid_road(spark, d).withColumn("part", F.col("src") % 4).write.partitionBy("part").parquet(path)
    return spark.read.schema(N.EDGE_SCHEMA + ", part LONG").parquet(path)


@query(f"{G} SELECT src, dst, c_time FROM edges WHERE c_time BETWEEN 100 AND 200 AND c_crossings IN (1) AND src % 2 = 0")
def edges_filter(spark, d):
    return N.grid_road(spark, d).where(F.col("c_time").between(100, 200) & F.col("c_crossings").isin(1) & (F.col("src") % 2 == 0)).select("src", "dst", "c_time")


@query("SELECT c_custkey, c_name FROM customer WHERE c_acctbal BETWEEN 1000 AND 2000 AND c_name LIKE '%1%'")
def customers_band(spark, d):
    return t(spark, d, "customer").where(F.col("c_acctbal").between(1000, 2000) & F.col("c_name").like("%1%")).select("c_custkey", "c_name")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def customers_without_orders(spark, d):
    return t(spark, d, "customer").join(t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query(f"{TR} SELECT e.src, n1.n_name AS from_name, e.dst, n2.n_name AS to_name, c_price FROM trade e JOIN nation n1 ON n1.n_nationkey = e.src JOIN nation n2 ON n2.n_nationkey = e.dst")
def anchors_broadcast_join(spark, d):
    n = t(spark, d, "nation").select("n_nationkey", "n_name")  # 25 rows at any scale
    a, b = F.broadcast(n.select(F.col("n_nationkey").alias("src"), F.col("n_name").alias("from_name"))), F.broadcast(n.select(F.col("n_nationkey").alias("dst"), F.col("n_name").alias("to_name")))
    return N.trade(spark, d).join(a, "src").join(b, "dst").select("src", "from_name", "dst", "to_name", "c_price")


@query(f"{TR}, o AS (SELECT * FROM trade WHERE c_price % 2 = 0), n AS (SELECT src, dst, c_price + 1 AS c_price FROM trade WHERE dst % 2 = 0) SELECT coalesce(o.src, n.src) AS src, coalesce(o.dst, n.dst) AS dst, least(o.c_price, n.c_price) AS c_price FROM o FULL JOIN n ON o.src = n.src AND o.dst = n.dst")
def state_full_outer(spark, d):
    e = N.trade(spark, d)
    o = e.where("c_price % 2 = 0").select("src", "dst", F.col("c_price").alias("p1"))
    n = e.where("dst % 2 = 0").select("src", "dst", (F.col("c_price") + 1).alias("p2"))
    return o.join(n, ["src", "dst"], "full").select("src", "dst", F.least("p1", "p2").alias("c_price"))


@query("SELECT p.p_partkey, count(*) AS pairs FROM part p JOIN part q ON p.p_brand = q.p_brand AND q.p_retailprice BETWEEN p.p_retailprice AND p.p_retailprice + 5 AND p.p_partkey <> q.p_partkey GROUP BY p.p_partkey")
def range_band_join(spark, d):
    """Pairs are counted by two ranks in a sort by price, so a brand costs its rows and not the square of them."""
    p = t(spark, d, "part").select("p_partkey", "p_brand", "p_retailprice").where(F.col("p_partkey").isNotNull() & F.col("p_brand").isNotNull() & F.col("p_retailprice").isNotNull())
    upto = Window.partitionBy("p_brand").orderBy("p_retailprice").rangeBetween(Window.unboundedPreceding, 5)
    below = Window.partitionBy("p_brand").orderBy("p_retailprice")
    own = Window.partitionBy("p_brand", "p_partkey").orderBy("p_retailprice").rangeBetween(0, 5)  # rows of the same key, which are no pairs
    n = p.withColumn("pairs", F.count(F.lit(1)).over(upto) - F.rank().over(below) + 1).withColumn("pairs", F.col("pairs") - F.count(F.lit(1)).over(own))
    return n.groupBy("p_partkey").agg(F.sum("pairs").alias("pairs")).where("pairs > 0")


@query("SELECT e.event_id, coalesce((SELECT max_by(struct_pack(v := round(u.value * 100)::BIGINT), struct_pack(a := u.ts, b := u.event_id)).v FROM events u WHERE u.user_id = e.user_id AND u.event_type = 'purchase' AND (u.ts < e.ts OR (u.ts = e.ts AND u.event_id < e.event_id))), -1) AS last_value FROM events e")
def cost_asof_events(spark, d):
    """The user's last purchase value before each event."""
    e = t(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.round(F.col("value") * 100).cast("long")), True).over(w)
    return e.withColumn("last_value", last).select("event_id", F.coalesce("last_value", F.lit(-1)).alias("last_value"))


@query("SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts BETWEEN a.ts - INTERVAL 12 HOUR AND a.ts + INTERVAL 12 HOUR GROUP BY a.event_id")
def interval_join_events(spark, d):
    e = t(spark, d, "events").select("event_id", "user_id", "ts")
    o = e.select(F.col("event_id").alias("id2"), "user_id", F.col("ts").alias("ts2"))
    half = F.expr("INTERVAL 12 HOURS")
    return e.join(o, "user_id").where((F.col("event_id") != F.col("id2")) & F.col("ts2").between(F.col("ts") - half, F.col("ts") + half)).groupBy("event_id").agg(F.count(F.lit(1)).alias("near"))


@query(f"{G} SELECT src, count(*) AS degree, min(c_time) AS fastest, arg_min(dst, c_time * 1000000 + dst) AS fastest_to, max(c_distance) AS longest FROM edges GROUP BY src")
def agg_edge_costs(spark, d):
    return N.grid_road(spark, d).groupBy("src").agg(F.count(F.lit(1)).alias("degree"), F.min("c_time").alias("fastest"), F.min_by("dst", F.struct("c_time", "dst")).alias("fastest_to"), F.max("c_distance").alias("longest"))


@query(f"{G} SELECT count(DISTINCT src) AS tails, count(DISTINCT dst) AS heads, count(DISTINCT c_time) AS times FROM edges")
def agg_distinct_nodes(spark, d):
    return N.grid_road(spark, d).agg(F.countDistinct("src").alias("tails"), F.countDistinct("dst").alias("heads"), F.countDistinct("c_time").alias("times"))


_LI = "SELECT r_name, n_name, o_orderstatus, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _orders_by_place(spark, d):
    dims = t(spark, d, "nation").join(t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    o = t(spark, d, "orders").select("o_custkey", "o_orderstatus").join(t(spark, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    return o.join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey"))


@query(f"SELECT r_name, n_name, count(*) AS n FROM ({_LI}) GROUP BY ROLLUP (r_name, n_name)")
def rollup_trade(spark, d):
    return _orders_by_place(spark, d).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT r_name, c_mktsegment, o_orderstatus, count(*) AS n FROM ({_LI}) GROUP BY CUBE (r_name, c_mktsegment, o_orderstatus)")
def cube_trade(spark, d):
    return _orders_by_place(spark, d).cube("r_name", "c_mktsegment", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT r_name, o_orderstatus, count(*) AS n FROM ({_LI}) GROUP BY GROUPING SETS ((r_name), (o_orderstatus), ())")
def gsets_trade(spark, d):
    x = _orders_by_place(spark, d)
    return x.groupingSets([[F.col("r_name")], [F.col("o_orderstatus")], []], "r_name", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query(f"{G} SELECT src, dst, c_time, rk FROM (SELECT src, dst, c_time, row_number() OVER (PARTITION BY src ORDER BY c_time, dst) AS rk FROM edges) WHERE rk <= 2")
def win_topk_edges(spark, d):
    w = Window.partitionBy("src").orderBy("c_time", "dst")
    return N.grid_road(spark, d).select("src", "dst", "c_time", F.row_number().over(w).alias("rk")).where("rk <= 2")


@query("SELECT o_custkey, o_orderkey, CAST(sum(cents) OVER w AS BIGINT) AS running, rank() OVER r AS rnk, dense_rank() OVER r AS drnk, coalesce(lag(o_orderkey) OVER w, -1) AS before FROM (SELECT *, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders) WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), r AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_running_cost(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    r = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    o = t(spark, d, "orders").withColumn("cents", F.round(F.col("o_totalprice") * 100).cast("long"))
    return o.select("o_custkey", "o_orderkey", F.sum("cents").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.rank().over(r).alias("rnk"), F.dense_rank().over(r).alias("drnk"), F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"))


@query(f"{G} SELECT src, dst, count(*) OVER (PARTITION BY src % 50 ORDER BY c_time RANGE BETWEEN 20 PRECEDING AND 20 FOLLOWING) AS near FROM edges")
def win_range_frame(spark, d):
    w = Window.partitionBy(F.col("src") % 50).orderBy("c_time").rangeBetween(-20, 20)
    return N.grid_road(spark, d).select("src", "dst", F.count(F.lit(1)).over(w).alias("near"))


@query(f"{G} SELECT src, dst, c_penalised FROM edges ORDER BY c_penalised DESC, src, dst LIMIT 20")
def topk_edges(spark, d):
    return N.grid_road(spark, d).orderBy(F.desc("c_penalised"), "src", "dst").limit(20).select("src", "dst", "c_penalised")


@query(f"{oracle.front(C.columns('te'))} SELECT CAST(task_id AS BIGINT) AS task_id, c0 AS c_time, c1 AS c_energy FROM (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY c0 + c1, c0) AS r FROM front) WHERE r <= 2")
def topk_paths(spark, d):
    f = batch.path_front(N.grid_road(spark, d), T.task_list(spark, T.oracle_pairs(t(spark, d, "customer").count())), C.columns("te"))
    f = f.select("task_id", F.col("cost")[0].alias("c_time"), F.col("cost")[1].alias("c_energy")).distinct()
    return f.withColumn("r", F.row_number().over(Window.partitionBy("task_id").orderBy(F.col("c_time") + F.col("c_energy"), "c_time"))).where("r <= 2").drop("r")


def _sets(spark, d):
    e = N.grid_road(spark, d)
    return e.where("c_time < 120").select(F.col("src").alias("node")), e.where("c_crossings = 1").select(F.col("dst").alias("node"))


_SETS = f"{G}, a AS (SELECT src AS node FROM edges WHERE c_time < 120), b AS (SELECT dst AS node FROM edges WHERE c_crossings = 1)"


@query(f"{_SETS} SELECT node FROM a UNION SELECT node FROM b")
def visited_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@query(f"{_SETS} SELECT node FROM a INTERSECT ALL SELECT node FROM b")
def visited_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersectAll(b)


@query(f"{_SETS} SELECT node FROM a EXCEPT SELECT node FROM b")
def visited_except(spark, d):
    a, b = _sets(spark, d)
    return a.subtract(b)


@query(f"{G} SELECT src, dst, criterion, cost FROM edges UNPIVOT (cost FOR criterion IN (c_time, c_distance, c_crossings, c_penalised, c_energy))")
def criteria_unpivot(spark, d):
    return N.grid_road(spark, d).unpivot(["src", "dst"], C.ALL, "criterion", "cost")


@query("SELECT c_nationkey, count(*) FILTER (c_mktsegment = 'BUILDING') AS building, count(*) FILTER (c_mktsegment = 'MACHINERY') AS machinery FROM customer GROUP BY c_nationkey")
def criteria_pivot(spark, d):
    p = t(spark, d, "customer").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count(F.lit(1)))
    return p.select("c_nationkey", F.coalesce("BUILDING", F.lit(0)).alias("building"), F.coalesce("MACHINERY", F.lit(0)).alias("machinery"))


_NOT = "SELECT p_brand, p_partkey FROM part x WHERE NOT EXISTS (SELECT 1 FROM part o WHERE o.p_brand = x.p_brand AND o.p_size <= x.p_size AND o.p_retailprice <= x.p_retailprice AND (o.p_size < x.p_size OR o.p_retailprice < x.p_retailprice))"


@query(_NOT)
def front_not_exists_sql(spark, d):
    t(spark, d, "part").createOrReplaceTempView("rf_part")
    return spark.sql(_NOT.replace("FROM part", "FROM rf_part"))


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)")
def scalar_sub_best(spark, d):
    t(spark, d, "orders").createOrReplaceTempView("rf_orders")
    return spark.sql("SELECT o_orderkey FROM rf_orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM rf_orders)")


@query("SELECT c_custkey, CAST(floor(sqrt(abs(c_acctbal))) AS BIGINT) AS root, CAST(sign(c_acctbal) AS INTEGER) AS sgn, upper(substr(c_name, 1, 4)) AS head, md5(c_name) AS digest, length(c_name) AS n FROM customer")
def scalar_math(spark, d):
    return t(spark, d, "customer").select("c_custkey", F.floor(F.sqrt(F.abs("c_acctbal"))).cast("long").alias("root"), F.signum("c_acctbal").cast("int").alias("sgn"), F.upper(F.substring("c_name", 1, 4)).alias("head"), F.md5(F.col("c_name").cast("binary")).alias("digest"), F.length("c_name").cast("long").alias("n"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, strftime(o_orderdate, '%Y-%m') AS month, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def scalar_dates(spark, d):
    o = F.col("o_orderdate")
    return t(spark, d, "orders").select("o_orderkey", F.year(o).cast("long").alias("y"), F.quarter(o).cast("long").alias("q"), F.date_format(o, "yyyy-MM").alias("month"), F.datediff(o, F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("SELECT page_id, href, count(*) AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) GROUP BY page_id, href")
def page_links(spark, d):
    p = t(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return p.groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT page_id, split_part(url, '/', 3) AS host, split_part(url, '/', 4) AS first FROM pages")
def url_parts(spark, d):
    return t(spark, d, "pages").select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.split_part("url", F.lit("/"), F.lit(4)).alias("first"))


@query()
def path_edges_explode(spark, d):
    f = batch.path_front(N.grid_road(spark, d), T.task_list(spark, [(0, 5)]), C.columns("te"))
    return f.select("task_id", F.posexplode("path").alias("position", "node"))


@query("SELECT c_custkey, list_sort([c_custkey % 7, c_custkey % 5, c_custkey % 3])::VARCHAR AS a, list_sum([c_custkey % 7, c_custkey % 5, c_custkey % 3])::BIGINT AS s, len(list_distinct([c_custkey % 7, c_custkey % 5, c_custkey % 3])) AS u FROM customer")
def path_arrays(spark, d):
    k = F.col("c_custkey")
    a = F.array(k % 7, k % 5, k % 3)
    return t(spark, d, "customer").select("c_custkey", F.concat(F.lit("["), F.array_join(F.transform(F.array_sort(a), lambda x: x.cast("string")), ", "), F.lit("]")).alias("a"), D.vec_total(a).alias("s"), F.size(F.array_distinct(a)).cast("long").alias("u"))


@query(f"{G} SELECT src, dst, c_time AS time, c_energy AS energy FROM edges")
def cost_map(spark, d):
    m = N.grid_road(spark, d).select("src", "dst", F.create_map(F.lit("time"), "c_time", F.lit("energy"), "c_energy").alias("m"))
    return m.select("src", "dst", F.col("m")["time"].alias("time"), F.col("m")["energy"].alias("energy"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def event_props_json(spark, d):
    return t(spark, d, "events").select("event_id", F.from_json("props", "k LONG")["k"].alias("k"))


@query(f"{oracle.front(C.columns('te'))}, s AS (SELECT task_id, count(*) AS n FROM front GROUP BY task_id) SELECT CAST(n AS BIGINT) AS front_size, count(*) AS tasks FROM s GROUP BY n")
def hist_front_sizes(spark, d):
    f = batch.path_front(N.grid_road(spark, d), T.task_list(spark, T.oracle_pairs(t(spark, d, "customer").count())), C.columns("te"))
    return f.select("task_id", "cost").distinct().groupBy("task_id").agg(F.count(F.lit(1)).alias("front_size")).groupBy("front_size").agg(F.count(F.lit(1)).alias("tasks"))


@query(f"{TR} SELECT a.src, a.dst AS dst1, b.dst AS dst2 FROM trade a JOIN trade b ON a.src = b.src AND a.dst <> b.dst WHERE {oracle.dominated_by(['a.c_price', 'a.c_lag'], ['b.c_price', 'b.c_lag'])}")
def sql_fn_dominates(spark, d):
    D.register_sql(spark)
    N.trade(spark, d).createOrReplaceTempView("rf_trade")
    return spark.sql("SELECT a.src, a.dst AS dst1, b.dst AS dst2 FROM rf_trade a JOIN rf_trade b ON a.src = b.src AND a.dst <> b.dst WHERE dominates(array(a.c_price, a.c_lag), array(b.c_price, b.c_lag))")


@query(f"{TR} SELECT src, dst, c_price + 2 * c_lag AS total FROM trade")
def udf_path_cost(spark, d):
    @F.pandas_udf("long")
    def path_cost(price: pd.Series, lag: pd.Series) -> pd.Series:
        return price + 2 * lag

    return N.trade(spark, d).select("src", "dst", path_cost("c_price", "c_lag").alias("total"))


@query(f"{TR} SELECT src, count(*) AS front_size FROM trade x WHERE NOT EXISTS (SELECT 1 FROM trade o WHERE o.src = x.src AND {oracle.dominated_by(['o.c_price', 'o.c_lag'], ['x.c_price', 'x.c_lag'])}) GROUP BY src")
def udaf_front_size(spark, d):
    @F.pandas_udf("long")
    def front_size(price: pd.Series, lag: pd.Series) -> int:
        rows = list(zip(price, lag, strict=True))
        return sum(not any(a <= x and b <= y and (a < x or b < y) for a, b in rows) for x, y in rows)

    return N.trade(spark, d).groupBy("src").agg(front_size("c_price", "c_lag").alias("front_size"))


@query("SELECT c_custkey, unnest([c_custkey, c_custkey + 1, c_custkey + 2]) AS node FROM customer")
def udtf_expand_path(spark, d):
    @F.udtf(returnType="node: long")
    class Expand:
        def eval(self, path: list) -> Iterator:
            for n in path:
                yield (n,)

    spark.udtf.register("rf_expand_path", Expand)
    t(spark, d, "customer").createOrReplaceTempView("rf_few")
    return spark.sql("SELECT c_custkey, x.node FROM rf_few, LATERAL rf_expand_path(array(c_custkey, c_custkey + 1, c_custkey + 2)) x")


def register_views(spark: SparkSession, d: str) -> None:
    """Views edges and local_tasks, and the SQL functions."""
    N.grid_road(spark, d).createOrReplaceTempView("rf_edges_view")
    T.local(spark, d).createOrReplaceTempView("rf_local_tasks")
    D.register_sql(spark)


def path_front_sql(spark: SparkSession, d: str, s: int, target: int, letters: str) -> DataFrame:
    """The path front of one query as a view for further SQL."""
    names = C.columns(letters)
    f = batch.path_front(N.grid_road(spark, d), T.task_list(spark, [(s, target)]), names)
    out = f.select(*(F.col("cost")[i].alias(n) for i, n in enumerate(names)), F.to_json(F.col("path")).alias("path"), "n_hops")
    out.createOrReplaceTempView("rf_path_front")
    return out


@query(f"{oracle.front(C.columns('te'))} SELECT DISTINCT c0 AS c_time, c1 AS c_energy FROM front WHERE task_id = 1")
def sql_path_front(spark, d):
    path_front_sql(spark, d, 0, min(5, t(spark, d, "customer").count() - 1), "te")
    return spark.sql("SELECT DISTINCT c_time, c_energy FROM rf_path_front")


