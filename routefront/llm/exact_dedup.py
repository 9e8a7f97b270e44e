"""Exact dedup with a heavy-hitter split: frequent digests are settled on the map side, the others by an ordinary shuffle.

Only DataFrame functions. `DataFrame.freqItems` is Spark's Misra-Gries summary (the Karp-Schenker-Papadimitriou
form): with support s it keeps at most 1/s counters a task and misses no digest above s of all rows. Its candidates
are verified by an exact, map-side combined count; the verified winners number at most 1/s, so their broadcast is
bounded whatever the input. Rows of a frequent digest never reach the shuffle.

Cases: a null text counts as empty; empty texts equal each other; of repeated rows with one doc_id a single row
stays; a null doc_id sorts after all others and keep_id is null only if a whole group has none; an empty table gives
an empty result; only doc_id and text are read, so extra columns can have any names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

#: Share of all rows above which a digest is settled on the map side; at most 1/SUPPORT winners are broadcast.
SUPPORT = 0.001


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), "[\\x20\\x09-\\x0D]+", " ")


def digest(text: Column) -> Column:
    return F.sha2(normalised(text), 256)


def frequent(rows: DataFrame, key: str, support: float = SUPPORT) -> DataFrame:
    """Verified frequent keys with count and the first (doc_id, row) of each; at most 1/support rows."""
    found = rows.freqItems([key], support).select(F.explode(f"{key}_freqItems").alias(key)).distinct()
    most = F.lit(support) * F.lit(rows.count())
    return (
        rows.join(F.broadcast(found), key, "left_semi")
        .groupBy(key)
        .agg(F.count(F.lit(1)).alias("__rf_n"), F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "__rf_row")).alias("__rf_first"))
        .where(F.col("__rf_n") > most)
    )


def groups(docs: DataFrame, support: float = SUPPORT) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = materialise(docs.select("doc_id", digest(F.col("text")).alias("text_sha256")).withColumn("__rf_row", F.monotonically_increasing_id()), "digests")
    heavy = materialise(frequent(rows, "text_sha256", support), "heavy")
    w = Window.partitionBy("text_sha256")
    order = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "__rf_row")
    rest = rows.join(F.broadcast(heavy), "text_sha256", "left_anti").withColumns({"__rf_n": F.count(F.lit(1)).over(w), "__rf_first": F.min(order).over(w)})
    settled = rows.join(F.broadcast(heavy), "text_sha256")
    return rest.unionByName(settled).select(
        "doc_id",
        F.col("__rf_first.doc_id").alias("keep_id"),
        F.col("__rf_n").alias("group_size"),
        (F.col("__rf_row") == F.col("__rf_first.__rf_row")).alias("kept"),
        "text_sha256",
    )


def deduplicate(docs: DataFrame, support: float = SUPPORT) -> DataFrame:
    """docs without its later copies, all columns kept. The texts cross one shuffle at most, those of frequent digests none."""
    own = docs.withColumns({"__rf_digest": digest(F.col("text")), "__rf_row": F.monotonically_increasing_id()})
    keys = materialise(own.select("doc_id", "__rf_digest", "__rf_row"), "digests")
    heavy = materialise(frequent(keys, "__rf_digest", support).select("__rf_digest", F.col("__rf_first.doc_id").alias("__rf_keep")), "heavy")
    first = Window.partitionBy("__rf_digest").orderBy(F.col("doc_id").asc_nulls_last())
    one = lambda df: df.withColumn("__rf_rank", F.row_number().over(first)).where(F.col("__rf_rank") == 1)
    rest = own.join(F.broadcast(heavy.select("__rf_digest")), "__rf_digest", "left_anti")
    winners = own.join(F.broadcast(heavy), (own["__rf_digest"] == heavy["__rf_digest"]) & own["doc_id"].eqNullSafe(heavy["__rf_keep"]), "left_semi")
    return one(rest).unionByName(one(winners)).select(*docs.columns)
