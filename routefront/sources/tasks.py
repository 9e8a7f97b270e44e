"""Task sets on the grid network: (task_id, src, dst)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .networks import grid_width, table


def task_list(spark: SparkSession, pairs: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame([(i + 1, s, t) for i, (s, t) in enumerate(pairs)], "task_id long, src long, dst long")


def _pairs(ends: DataFrame) -> DataFrame:
    """Ordered pairs of a fixed, small set of ends (27 or 10)."""
    a, b = ends.select(F.col("node").alias("src")), ends.select(F.col("node").alias("dst"))
    both = a.join(F.broadcast(b), F.col("src") != F.col("dst"))
    return both.select((F.row_number().over(Window.orderBy("src", "dst"))).cast("long").alias("task_id"), "src", "dst")


def local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ordered pairs of the 27 junctions of the central block whose row and column add up to a multiple of 3."""
    w = grid_width(spark, sf_dir)
    c = w // 2
    row, col = F.floor(F.col("c_custkey") / w), F.col("c_custkey") % w
    inside = (F.abs(row - c) <= 4) & (F.abs(col - c) <= 4) & ((row + col) % 3 == 0)
    return _pairs(table(spark, sf_dir, "customer").where(inside).select(F.col("c_custkey").alias("node")))


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ordered pairs of ten junctions, the richest of each tenth of the keys."""
    tenth = Window.orderBy("c_custkey")
    rich = Window.partitionBy("tile").orderBy(F.desc("c_acctbal"), "c_custkey")
    t = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal").withColumn("tile", F.ntile(10).over(tenth))
    return _pairs(t.withColumn("rank", F.row_number().over(rich)).where("rank = 1").select(F.col("c_custkey").alias("node")))


def mini(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tasks among the first five ends of the local set."""
    ends = local(spark, sf_dir).select("src").distinct().orderBy("src").limit(5).select(F.col("src").alias("node"))
    return _pairs(ends)


def oracle_pairs(n: int) -> list[tuple[int, int]]:
    """Three tasks of rising length on a grid of n junctions."""
    return [(0, min(5, n - 1)), (0, n * 4 // 15), (20 % n, n * 3 // 10)]
