"""Networks carried by the given tables, and edge-list files.

Every builder returns (src, dst, costs...) with whole non-negative costs, none of them all zero.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import criteria as C


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def grid_width(spark: SparkSession, sf_dir: str) -> int:
    return math.ceil(math.sqrt(table(spark, sf_dir, "customer").count()))


def grid_nodes(spark: SparkSession, sf_dir: str, width: int | None = None) -> DataFrame:
    w = F.lit(width or grid_width(spark, sf_dir))
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("node"), (F.col("c_custkey") % w).cast("int").alias("x"), F.floor(F.col("c_custkey") / w).cast("int").alias("y"))


def grid_road(spark: SparkSession, sf_dir: str, width: int | None = None) -> DataFrame:
    """The grid road network: customers are junctions, neighbours in the grid are joined by edges with five costs."""
    w = F.lit(width or grid_width(spark, sf_dir)).cast("long")
    k = F.col("c_custkey")
    cust = table(spark, sf_dir, "customer").select(k, "c_nationkey", "c_mktsegment", F.floor(F.col("c_acctbal") / 100).cast("long").alias("altitude"))
    right = F.when((k + 1) % w != 0, k + 1)
    left = F.when(k % w != 0, k - 1)
    tail = cust.select(F.col("c_custkey").alias("src"), "c_mktsegment", F.col("altitude").alias("from_altitude"), F.explode(F.array_compact(F.array(right, left, k + w, k - w))).alias("dst"))
    low, high = F.least("src", "dst"), F.greatest("src", "dst")
    kept = tail.where((high - low == 1) | (low % 3 != 0) | (F.col("src") % w == 0))
    head = cust.select(F.col("c_custkey").alias("dst"), F.col("c_nationkey").alias("nation"), F.col("altitude").alias("to_altitude"))
    speed = F.element_at(F.create_map(*(F.lit(x) for kv in C.SPEEDS.items() for x in kv)), F.col("c_mktsegment"))
    e = kept.join(head, "dst").withColumn("c_distance", (100 + (low * 7919 + high * 104729) % 151).cast("long"))
    e = e.withColumn("c_time", C.duration(F.col("c_distance"), speed))
    return e.select(
        "src", "dst", "c_time", "c_distance", C.crossings(F.col("nation")).alias("c_crossings"), C.penalised(F.col("c_time"), F.col("nation")).alias("c_penalised"), C.energy(F.col("c_distance"), F.col("to_altitude") - F.col("from_altitude")).alias("c_energy")
    )


def city(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grid network cut to the block around its centre, as far as 0.23 of its width (4 cells at least)."""
    w = grid_width(spark, sf_dir)
    reach = max(4, math.floor(0.23 * w))
    near = lambda c: (F.abs(F.floor(F.col(c) / w) - w // 2) <= reach) & (F.abs(F.col(c) % w - w // 2) <= reach)
    return grid_road(spark, sf_dir, w).where(near("src") & near("dst"))


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations that trade: mean unit price (cents), mean lag in days, rarity of shipments, one hop."""
    t = lambda n: table(spark, sf_dir, n)
    lines = t("lineitem").select("l_orderkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    supplier = t("supplier").select("s_suppkey", "s_nationkey")
    rows = (
        lines.join(t("orders").select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(supplier) if supplier.count() <= 1_000_000 else supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        .where(F.col("s_nationkey") != F.col("c_nationkey"))
    )
    cents = F.floor(F.col("l_extendedprice") * 100 / F.col("l_quantity")).cast("long")
    lag = F.abs(F.datediff("l_shipdate", "o_orderdate")).cast("long")
    return rows.groupBy(F.col("s_nationkey").cast("long").alias("src"), F.col("c_nationkey").cast("long").alias("dst")).agg(
        F.floor(F.sum(cents) / F.count(F.lit(1))).cast("long").alias("c_price"),
        F.floor(F.sum(lag) / F.count(F.lit(1))).cast("long").alias("c_lag"),
        F.floor(F.lit(10000) / F.count(F.lit(1))).cast("long").alias("c_rarity"),
        F.lit(1).cast("long").alias("c_hop"),
    )


def part_flow(spark: SparkSession, sf_dir: str, fan: int = 3) -> DataFrame:
    """Parts that follow each other in an order; of every part the `fan` cheapest out-edges."""
    by_order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    nxt = lambda c: F.lead(c).over(by_order)
    rows = table(spark, sf_dir, "lineitem").select(
        F.col("l_partkey").alias("src"), nxt("l_partkey").alias("dst"), F.floor("l_extendedprice").cast("long").alias("c_price"), F.floor("l_quantity").cast("long").alias("c_quantity"), F.abs(F.datediff(nxt("l_shipdate"), F.col("l_shipdate"))).cast("long").alias("c_days")
    )
    rows = rows.where(F.col("dst").isNotNull() & (F.col("src") != F.col("dst")))
    cheap = Window.partitionBy("src").orderBy("c_price", "dst", "c_quantity", "c_days")
    return rows.withColumn("rank", F.row_number().over(cheap)).where(F.col("rank") <= fan).drop("rank")


def _nearest(pairs, k: int):
    """Of every pair of blocks the k nearest of each vector of the first one, as `vector_knn` orders them."""
    for pair in pairs:
        for row in range(pair.num_rows):
            (sa, la, a), (sb, lb, b) = ((x.field("id"), x.field("label"), _matrix(x.field("embedding"))) for x in (pair.column(c)[row].values for c in ("a", "b")))
            ids, others = sa.to_numpy(), sb.to_numpy()
            out = []
            for at in range(0, len(ids), 256):  # rows at once: their distances to a whole block are in memory
                x = a[at : at + 256]
                own = ids[at : at + 256]
                norms = (x * x).sum(1)[:, None] + (b * b).sum(1)
                rough = norms - 2 * x @ b.T
                rough[own[:, None] == others] = np.inf
                kth = np.partition(rough, min(k, len(others)) - 1, axis=1)[:, min(k, len(others)) - 1]
                # all that can round to the k-th distance or less: a unit of c_l2 more, and the error of the rough distances
                error = 1e-12 * norms.max() + 1e-300
                i, j = np.nonzero(rough <= ((np.sqrt(np.maximum(kth, 0) + error) + 1e-4) ** 2 + error)[:, None])
                near = own[i] != others[j]
                i, j = i[near], j[near]
                total = np.zeros(len(i))
                for axis in range(a.shape[1]):  # summed in the order of the coordinates
                    total += (x[i, axis] - b[j, axis]) ** 2
                exact = np.sqrt(total) * 10000
                cost = (np.floor(exact) + (exact - np.floor(exact) >= 0.5)).astype(np.int64)
                order = np.lexsort((others[j], cost, i))
                i, j, cost = i[order], j[order], cost[order]
                first = np.searchsorted(i, i)
                kept = np.arange(len(i)) - first < k
                out.append((i[kept] + at, j[kept], cost[kept]))
            i, j, cost = (np.concatenate(x) for x in zip(*out, strict=True))
            change = pc.cast(pc.not_equal(la.take(pa.array(i)), lb.take(pa.array(j))), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(others[j]), pa.array(cost), change], ["src", "dst", "c_l2", "c_change"])


def _matrix(embedding: pa.ListArray) -> np.ndarray:
    return embedding.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(embedding), -1)


def vector_knn(spark: SparkSession, sf_dir: str, k: int = 6, block: int = 4096) -> DataFrame:
    """Nearest neighbours by L2 of every embedding, in pairs of blocks of about `block` vectors; label change and hop as further costs.

    The embeddings have equal lengths and are not null.
    """
    v = table(spark, sf_dir, "embeddings")
    blocks = max(1, math.ceil(v.count() / block))
    packed = v.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("block")).agg(F.collect_list(F.struct(F.col("vec_id").alias("id"), "label", "embedding")).alias("rows"))
    both = lambda mine, other, name: packed.select(F.col("block").alias(mine), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias(other), F.col("rows").alias(name))
    pairs = both("ba", "bb", "a").join(both("bb", "ba", "b"), ["ba", "bb"]).select("a", "b")
    d = pairs.mapInArrow(lambda batches: _nearest(batches, k), "src long, dst long, c_l2 long, c_change long")
    near = Window.partitionBy("src").orderBy("c_l2", "dst")
    return d.withColumn("c_hop", F.lit(1).cast("long")).withColumn("rank", F.row_number().over(near)).where(F.col("rank") <= k).drop("rank")


def event_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event types that follow each other for a user: least gap in seconds, least change of value."""
    by_user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    nxt = lambda c: F.lead(c).over(by_user)
    e = table(spark, sf_dir, "events").select(
        F.col("event_type").alias("from_type"), nxt("event_type").alias("to_type"), (F.unix_timestamp(nxt("ts")) - F.unix_timestamp("ts")).alias("gap"), F.abs(F.round(nxt("value") * 100) - F.round(F.col("value") * 100)).cast("long").alias("change")
    )
    e = e.where(F.col("to_type").isNotNull())
    return e.groupBy("from_type", "to_type").agg(F.min("gap").cast("long").alias("c_gap"), F.min("change").alias("c_change"), F.count(F.lit(1)).alias("n"))


def project(edges: DataFrame, criteria: list[str]) -> DataFrame:
    """(src, dst, c0..): only the asked criteria, so the scan prunes the others."""
    return edges.select("src", "dst", *(F.col(c).cast("long").alias(f"c{i}") for i, c in enumerate(criteria)))


def validate(edges: DataFrame, criteria: list[str]) -> DataFrame:
    """One row of counts: edges, null, negative and all-zero costs, loops."""
    cols = [F.col(c) for c in criteria]
    null = F.coalesce(*(F.when(c.isNull(), F.lit(1)) for c in cols), F.lit(0))
    negative = F.coalesce(*(F.when(c < 0, F.lit(1)) for c in cols), F.lit(0))
    zero = F.when(F.greatest(*cols) == 0, 1).otherwise(0) if len(cols) > 1 else F.when(cols[0] == 0, 1).otherwise(0)
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum(null), F.lit(0)).alias("null_costs"), F.coalesce(F.sum(negative), F.lit(0)).alias("negative_costs"), F.coalesce(F.sum(zero), F.lit(0)).alias("zero_edges"), F.coalesce(F.sum(F.when(F.col("src") == F.col("dst"), 1).otherwise(0)), F.lit(0)).alias("loops"))


def check(edges: DataFrame, criteria: list[str]) -> DataFrame:
    """edges itself, or an error that names what is wrong with its costs."""
    r = validate(edges, criteria).first()
    for what in ("null_costs", "negative_costs", "zero_edges"):
        if r[what]:
            raise ValueError(f"{r[what]} edges have {what.replace('_', ' ')}")
    return edges


EDGE_SCHEMA = "src LONG, dst LONG, c_time LONG, c_distance LONG, c_crossings LONG, c_penalised LONG, c_energy LONG"


def read_edges(spark: SparkSession, path: str, kind: str = "csv", schema: str = EDGE_SCHEMA) -> DataFrame:
    reader = spark.read.schema(schema)
    return reader.csv(path, header=True) if kind == "csv" else reader.json(path) if kind == "json" else reader.parquet(path)


def write_layouts(edges: DataFrame, name: str, buckets: int = 64) -> None:
    """Two bucketed copies, by head and by tail, so that supersteps join without moving edges."""
    for key in ("dst", "src"):
        edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(f"{name}_by_{key}")
