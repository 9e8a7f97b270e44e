"""Edge-cost updates as a stream: events become updates, updates become current costs, tasks are answered anew."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import criteria as C
from ..plans import batch
from ..plans.loop import materialise, shared_dir
from ..sources import networks as N

EVENTS = "event_id LONG, ts TIMESTAMP, user_id LONG, event_type STRING, value DOUBLE, props STRING"


#: Events of a file of the replayed stream, about.
PER_FILE = 1_000_000


def event_stream(spark: SparkSession, sf_dir: str, files: int = 4, per_trigger: int = 1) -> DataFrame:
    """The events table replayed as files in the shared folder. The source reads files by their time of modification, so they are written one after another, a range of event times each: no row is late."""
    path = f"{shared_dir(spark).rstrip('/')}/events-{uuid.uuid4().hex}"
    e = N.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
    span = e.agg(F.unix_micros(F.min("ts")).alias("low"), F.unix_micros(F.max("ts")).alias("high"), F.count(F.lit(1)).alias("n")).first()
    low, files = span["low"] or 0, max(files, -(-span["n"] // PER_FILE))
    width = ((span["high"] or 0) - low) // files + 1
    e = materialise(e.withColumn("part", F.floor((F.unix_micros("ts") - low) / width).cast("int")), "events")
    for k in range(files):
        e.where((F.col("part") == k) | (F.lit(k == 0) & F.col("part").isNull())).drop("part").coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path)


def updates(events: DataFrame, edges: int) -> DataFrame:
    """(edge_id, ts, event_id, percent): an event slows one edge down or speeds it up, between half and one and a half."""
    return events.select((F.col("event_id") % edges).alias("edge_id"), "ts", "event_id", (F.lit(50) + F.floor(F.col("value")).cast("long") % 101).alias("percent"))


def run_to_memory(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over all its files; the result as a table."""
    spark = stream.sparkSession
    name = "rf_" + uuid.uuid4().hex
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_dir(spark).rstrip('/')}/stream-{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def run_batches(stream: DataFrame, fn: Callable[[DataFrame, int], None]) -> None:
    spark = stream.sparkSession
    q = stream.writeStream.foreachBatch(fn).option("checkpointLocation", f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}").trigger(availableNow=True).start()
    q.awaitTermination()


def latest(updates_: DataFrame) -> DataFrame:
    """Current percentage of every edge: the update of the latest time (then event id)."""
    return updates_.groupBy("edge_id").agg(F.max_by("percent", F.struct("ts", "event_id")).alias("percent"))


def numbered(edges: DataFrame) -> DataFrame:
    """Edges with an id that does not depend on partitions: their order by (src, dst)."""
    from pyspark.sql import Window

    per = Window.partitionBy("src").orderBy("dst")
    start = edges.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    before = start.withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("src").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    return edges.join(before, "src").withColumn("edge_id", F.col("before") + F.row_number().over(per) - 1).drop("before")


def reprice(edges: DataFrame, current: DataFrame) -> DataFrame:
    """Time and penalised time of edges under the current percentages; other costs stay."""
    j = edges.join(current, "edge_id", "left")
    p = F.coalesce("percent", F.lit(100))
    return j.select("src", "dst", *((F.greatest(F.lit(1), F.floor(F.col(c) * p / 100)).cast("long").alias(c) if c in ("c_time", "c_penalised") else F.col(c)) for c in C.ALL))


def answer_each_batch(spark: SparkSession, sf_dir: str, tasks: DataFrame, letters: str) -> DataFrame:
    """Registered tasks answered after every micro-batch of updates; bounds are computed anew each time."""
    edges = batch.keep(numbered(N.grid_road(spark, sf_dir)), "numbered")
    n = edges.count()
    seen: list[DataFrame] = []
    out: list[DataFrame] = []

    def one(df: DataFrame, k: int) -> None:
        seen.append(batch.keep(updates(df, n), f"updates-{k}"))
        every = seen[0]
        for more in seen[1:]:
            every = every.unionByName(more)
        names = C.columns(letters)
        f = batch.path_front(reprice(edges, latest(every)), tasks, names)
        out.append(batch.keep(f.select(F.lit(k).cast("long").alias("batch"), "task_id", *(F.col("cost")[i].alias(c) for i, c in enumerate(names))).distinct(), f"answers-{k}"))

    run_batches(event_stream(spark, sf_dir), one)
    result = out[0]
    for more in out[1:]:
        result = result.unionByName(more)
    return result
