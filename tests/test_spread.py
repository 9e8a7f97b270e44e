"""Few tasks are dealt out one by one."""

import pytest
from pyspark.sql import functions as F

from routefront.plans import batch
from routefront.sources import tasks as T


@pytest.mark.parametrize("n", [3, 6, 8, 12])
def test_three_tasks_are_in_three_parts(spark, n):
    parts = batch._spread(T.task_list(spark, T.oracle_pairs(900)), n).select("task_id", F.spark_partition_id().alias("part")).collect()
    assert sorted(r["task_id"] for r in parts) == [1, 2, 3] and len({r["part"] for r in parts}) == 3


def test_many_tasks_are_dealt_evenly(spark):
    rows = batch._spread(T.task_list(spark, [(i, i + 1) for i in range(702)]), 6).groupBy(F.spark_partition_id().alias("part")).count().collect()
    assert len(rows) == 6 and max(r["count"] for r in rows) <= 2 * 702 // 6


def test_no_tasks(spark):
    assert batch._spread(T.task_list(spark, [(1, 2)]).where("false"), 6).count() == 0
