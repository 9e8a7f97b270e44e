"""Substring dedup by content-defined chunking with a gear rolling hash.

A cut falls where bits of the gear hash of the last `WINDOW` bytes are zero, so cuts move with the content and an
insertion disturbs only the chunks it touches. Chunks are compared by 64-bit digest over the whole corpus; a chunk that
an earlier document has is a repeat, and a run of neighbouring repeats of at least `min_words` words is a repeated
passage. A single false match of two digests is one chunk and never makes a run. The first document (smallest doc_id)
keeps the passage. With `within`, a later place in the same document is a repeat too; without it, repeats that no other
document has stay.

A digest's first document comes from a map-side combined minimum, so a passage that a third of all documents share is one
row per task in that shuffle. Digests above `SUPPORT` of all chunks find their first document by a broadcast of at most
1/SUPPORT rows, the others by a join.

Cases: null and empty texts have no chunks; rows with equal doc_id and text (15 bits of its hash) count as one document; a null doc_id comes
after all others; a text without any cut is cut every `MOST` bytes; an empty table gives an empty result; other columns
of a table pass through `remove_repeats` unchanged, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE, map_texts, materialise, mix64, text_views

#: Bytes the hash looks back on, bits that must be zero at a cut, least and most bytes of a chunk.
WINDOW, BITS, LEAST, MOST = 16, 4, 20, 128
#: Words that a run of repeated chunks must hold. The passage around it is longer by up to a chunk at either end.
MIN_WORDS = 20

_GEAR = (mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) & np.uint64(0xFFFF)).astype(np.uint16)
_MASK = np.uint16(((1 << BITS) - 1) << (16 - BITS))


def gear(buf: np.ndarray) -> np.ndarray:
    """Gear hash (h = 2h + table[byte]) modulo 2**16 at every byte: the last 16 bytes decide it. Doubling windows, no loop over bytes."""
    h = _GEAR[buf]
    width = 1
    while width < WINDOW:
        g = h.copy()
        g[width:] += h[:-width] << np.uint16(width)
        h, width = g, 2 * width
    return h


def cuts(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chunk borders of the concatenated texts, and the document of each chunk. Borders never split a UTF-8 character."""
    inner = (buf & 0xC0) == 0x80
    at = np.flatnonzero((gear(buf) & _MASK) == 0) + 1 if len(buf) else np.zeros(0, np.int64)
    for _ in range(3):
        at = at + (inner[np.minimum(at, len(buf) - 1)] & (at < len(buf)))
    at = np.unique(at).tolist()
    borders, owner = [], []
    k, many = 0, len(at)
    for doc, (begin, end) in enumerate(zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)):
        last = begin
        while last < end:
            while k < many and at[k] < last + LEAST:
                k += 1
            cut = min(at[k] if k < many else end, last + MOST, end)
            while cut < end and inner[cut]:
                cut += 1
            borders.append(last)
            owner.append(doc)
            last = cut
    return np.array(borders, np.int64), np.array(owner, np.int64)


#: A chunk's place in one number: 15 bits of the text's hash (`version`), 31 of its first byte, 8 each of bytes and words, and whether its own text has it before.
CHUNKS = "doc_id long, span long, digest long"
#: Share of all chunks above which a digest is settled on the map side; at most 1/SUPPORT of them are broadcast.
SUPPORT = 0.0005


def version_of(text: Column) -> Column:
    """Tells texts of one doc_id apart."""
    return F.shiftrightunsigned(F.xxhash64(text), 49)


def chunks(docs: DataFrame) -> DataFrame:
    """One row per chunk, three numbers each: all that crosses the shuffles."""

    def fn(batch: pa.RecordBatch):
        buf, offs = text_views(batch.column(1))
        start, doc = cuts(buf, offs)
        if not len(start):
            return
        end = np.append(start[1:], len(buf))
        word = ~SPACE[buf]
        begins = word.copy()
        begins[1:] &= ~word[:-1]
        upto = np.append(0, np.cumsum(begins))
        view = memoryview(np.ascontiguousarray(buf))
        digest = np.fromiter((xxhash.xxh3_64_intdigest(view[a:b]) for a, b in zip(start.tolist(), end.tolist(), strict=True)), np.uint64, len(start))
        order = np.lexsort((digest, doc))
        again = np.zeros(len(start), np.int64)
        again[order[1:]] = (digest[order[1:]] == digest[order[:-1]]) & (doc[order[1:]] == doc[order[:-1]])  # lexsort is stable: the first in the text comes first
        version = batch.column(2).to_numpy()
        span = version[doc] << 48 | (start - offs[doc]) << 17 | (end - start) << 9 | (upto[end] - upto[start]) << 1 | again
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(doc)), pa.array(span), pa.array(digest.view(np.int64))], ["doc_id", "span", "digest"])

    return map_texts(docs, [F.col("doc_id").cast("long").alias("doc_id"), "text", version_of(F.col("text")).alias("version")], fn, CHUNKS, 1 << 20)


def _bits(column: str, low: int, count: int) -> Column:
    return F.shiftright(F.col(column), low).bitwiseAND(F.lit((1 << count) - 1))


def repeated_passages(docs: DataFrame, min_words: int = MIN_WORDS, within: bool = False, support: float = SUPPORT) -> DataFrame:
    """doc_id, version, start, length (bytes), words, chunks, first_doc_id: one row per passage that an earlier document (within: or an earlier place of its own) has."""
    made = materialise(chunks(docs), "chunks")
    doc, tag, again = F.coalesce("doc_id", F.lit((1 << 63) - 1)), _bits("span", 48, 15), _bits("span", 0, 1)
    owners = made.groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.min(doc).alias("first"), F.max(doc).alias("other"), F.min(tag).alias("first_tag"), F.max(tag).alias("other_tag"), F.max(again).alias("within"))
    inside = F.lit(within) & (F.col("within") == 1)
    owners = materialise(owners.where((F.col("first") != F.col("other")) | (F.col("first_tag") != F.col("other_tag")) | inside).drop("other_tag", "within"), "owners")
    # a digest that a large share of documents has is no key of a shuffle: its owner is broadcast
    most = F.lit(support) * F.lit(made.count())
    heavy = materialise(owners.where(F.col("n") > most), "heavy")
    rest = made.join(F.broadcast(heavy.select("digest")), "digest", "left_anti").join(owners.where(F.col("n") <= most).hint("merge"), "digest")
    later = (doc != F.col("first")) | ((F.col("first") == F.col("other")) & (tag != F.col("first_tag"))) | (F.lit(within) & (again == 1))
    repeats = made.join(F.broadcast(heavy), "digest").unionByName(rest).where(later)
    repeats = repeats.select("doc_id", _bits("span", 48, 15).alias("version"), _bits("span", 17, 31).alias("start"), _bits("span", 9, 8).alias("length"), _bits("span", 1, 8).alias("words"), F.col("first").alias("first_doc_id"))
    repeats = repeats.dropDuplicates(["doc_id", "version", "start"])  # rows repeated whole
    order = Window.partitionBy("doc_id", "version").orderBy("start")
    gap = F.lag(F.col("start") + F.col("length"), 1, -1).over(order) != F.col("start")
    runs = repeats.withColumn("gap", gap.cast("int")).withColumn("run", F.sum("gap").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    spans = runs.groupBy("doc_id", "version", "run").agg(F.min("start").alias("start"), F.sum("length").alias("length"), F.sum("words").alias("words"), F.count(F.lit(1)).alias("chunks"), F.min("first_doc_id").alias("first_doc_id"))
    return spans.where(F.col("words") >= min_words).drop("run")


def without(text: Column, spans: Column) -> Column:
    """A text without byte ranges (ascending structs of start and length, whole characters)."""
    raw = text.cast("binary")
    begin = F.concat(F.array(F.lit(0).cast("long")), F.transform(spans, lambda s: s["start"] + s["length"]))
    end = F.concat(F.transform(spans, lambda s: s["start"]), F.array(F.octet_length(text).cast("long")))
    kept = F.zip_with(begin, end, lambda a, b: F.decode(F.substring(raw, (a + 1).cast("int"), (b - a).cast("int")), "UTF-8"))
    return F.array_join(kept, "")


def remove_repeats(docs: DataFrame, min_words: int = MIN_WORDS, within: bool = False) -> DataFrame:
    """docs with every repeated passage cut out of the later documents; a column n_chars follows the text. Whole rows stay in the JVM."""
    spans = repeated_passages(docs, min_words, within).groupBy("doc_id", "version").agg(F.sort_array(F.collect_list(F.struct("start", "length"))).alias("__rf_spans"))
    spans = materialise(spans, "spans").withColumnsRenamed({"doc_id": "__rf_doc", "version": "__rf_version"})
    joined = docs.withColumn("__rf_text", F.col("text")).join(spans, docs["doc_id"].cast("long").eqNullSafe(spans["__rf_doc"]) & (version_of(docs["text"]) == spans["__rf_version"]), "left")
    cut = F.when(F.col("__rf_spans").isNull(), F.col("__rf_text")).otherwise(without(F.col("__rf_text"), F.col("__rf_spans")))
    new = {"text": cut}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("__rf_spans").isNull(), docs["n_chars"]).otherwise(F.char_length(cut).cast(docs.schema["n_chars"].dataType))
    return joined.select(*(new[c].alias(c) if c in new else docs[c] for c in docs.columns))
