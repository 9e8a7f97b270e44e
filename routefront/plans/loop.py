"""Superstep runner: iterate a state table until a condition holds, cutting its lineage in the shared folder each time."""

from __future__ import annotations

import atexit
import os
import re
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []


def _delete(spark: SparkSession, path: str) -> None:
    try:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may be gone
        return


@atexit.register
def _forget() -> None:
    for spark, path in _written:
        _delete(spark, path)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a folder of our own only where it is unset and driver and executors are one process."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return at or f"file:///tmp/checkpoints/routefront-{os.getpid()}"


def materialise(df: DataFrame, label: str) -> DataFrame:
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/routefront-{uuid.uuid4().hex}/{label}"
    df.write.parquet(path)
    _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._routefront_path = path
    return out


def release(df: DataFrame) -> None:
    """Drop a table that no later step reads."""
    if path := getattr(df, "_routefront_path", None):
        _delete(df.sparkSession, path)


@dataclass
class Trace:
    supersteps: int = 0
    seconds: float = 0.0
    open_rows: list[int] = field(default_factory=list)
    timed_out: bool = False


def run_supersteps(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], open_count: Callable[[DataFrame], int], *, most: int = 10_000, limit_s: float | None = None, label: str = "state") -> tuple[DataFrame, Trace]:
    """Apply `step` until nothing is open. Only the count of open rows reaches the driver.

    A run that meets `most` or `limit_s` is flagged as timed out; it never drops rows.
    """
    trace, began = Trace(), time.monotonic()
    state = materialise(state, f"{label}-0")
    held = [state]
    while (n := open_count(state)) > 0:
        trace.open_rows.append(n)
        if trace.supersteps >= most or (limit_s is not None and time.monotonic() - began > limit_s):
            trace.timed_out = True
            break
        trace.supersteps += 1
        state = materialise(step(state, trace.supersteps), f"{label}-{trace.supersteps}")
        held.append(state)
        if len(held) > 2:
            release(held.pop(0))
    trace.seconds = time.monotonic() - began
    return state, trace
