"""Shared plumbing of the text operators: shared-folder tables, Arrow slices, vectorised ASCII-space tokens."""

from __future__ import annotations

import atexit
import os
import re
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of every contract here: space and \x09-\x0D. bytes.split() splits on exactly these.
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir as the session has it; one of our own only if unset and the master is local."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return at or f"file:///tmp/checkpoints/routefront-{os.getpid()}"


def _forget() -> None:
    for spark, path in _written:
        try:
            jvm = spark.sparkContext._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session may be gone by then; the folder is the cluster's scratch space
            return


atexit.register(_forget)


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write df once as Parquet in the shared folder and read it back: the lineage ends there, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/routefront-{uuid.uuid4().hex}/{label}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words_hash(text: Column) -> Column:
    """64-bit hash of a text's words (null: of none), whatever white space parts them."""
    return F.xxhash64(F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), "[\\x20\\x09-\\x0D]+", " ")))


def id_bucket(col: str, modulus: int):
    """crc32 of doc_id as text, modulo modulus (null id: null)."""
    return F.crc32(F.col(col).cast("string").cast("binary")) % F.lit(modulus)


def text_views(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and n+1 offsets into them; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offs, data = column.buffers()
    o = np.frombuffer(offs, np.int64, len(column) + 1, column.offset * 8) if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[o[0] : o[-1]], o - o[0]


def slices(batch: pa.RecordBatch, text: str, limit: int) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows of about limit bytes of text; a longer text stands alone, whole."""
    col = batch.column(batch.schema.get_field_index(text))
    size = pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    start, total = 0, 0
    for i, s in enumerate(size):
        if i > start and total + s > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(s)
    if start < len(size):
        yield batch.slice(start)


def map_texts(df: DataFrame, columns: list, fn: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]], schema: str, limit: int = 2 << 20, text: str = "text") -> DataFrame:
    """fn over slices of the chosen columns, on the executors; memory is bounded by limit and the longest text."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, text, limit):
                yield from fn(part)

    return df.select(*columns).mapInArrow(run, schema)


def text_column(fn: Callable[[pa.Array], pa.Array], kind: str, limit: int = 1 << 19):
    """A function of a text column: fn over slices of about limit bytes. Only the texts reach Python, the rest of a row stays where it is."""

    @F.arrow_udf(kind)
    def of(texts: pa.Array) -> pa.Array:
        batch = pa.RecordBatch.from_arrays([texts], ["text"])
        return pa.concat_arrays([fn(part.column(0)) for part in slices(batch, "text", limit)] or [fn(texts)])

    return of


def token_bounds(buf: np.ndarray, offs: np.ndarray, space: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and document index of every word (run of bytes outside `space`) of the concatenated texts."""
    if not len(buf):
        z = np.zeros(0, np.int64)
        return z, z, z
    word = ~space[buf]
    first = word.copy()
    first[1:] &= ~word[:-1]
    cuts = offs[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(buf))]
    first[cuts] |= word[cuts]
    last = word.copy()
    last[:-1] &= ~word[1:]
    last[cuts - 1] |= word[cuts - 1]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(offs, starts, "right") - 1


def mix64(x: np.ndarray) -> np.ndarray:
    """SplitMix64 finaliser (public domain), vectorised."""
    x = x.astype(np.uint64, copy=True)
    return mix_into(x, np.empty_like(x))


def mix_into(x: np.ndarray, temp: np.ndarray) -> np.ndarray:
    """mix64 in place; temp: room for as many numbers."""
    for bits, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB), (31, 1)):
        np.bitwise_xor(x, np.right_shift(x, np.uint64(bits), out=temp), out=x)
        if factor != 1:
            np.multiply(x, np.uint64(factor), out=x)
    return x


_BASE = 0x9E3779B97F4A7C15 | 1
_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
_powers: dict[str, np.ndarray] = {}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _powers.get("up")
    if have is None or len(have) < n:
        m = max(n, 1 << 16)
        inverse = pow(_BASE, -1, 1 << 64)
        for key, b in (("up", _BASE), ("down", inverse)):
            p = np.full(m, b, np.uint64)
            p[0] = 1
            _powers[key] = np.multiply.accumulate(p)
    return _powers["up"][:n], _powers["down"][:n]


def token_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit polynomial hashes of byte ranges, from one prefix sum modulo 2**64."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    up, down = _power(len(buf) + 1)
    prefix = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(_BYTE[buf] * up[:-1], out=prefix[1:])
    return mix64((prefix[ends] - prefix[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def lower_ascii(buf: np.ndarray) -> np.ndarray:
    return np.where((buf >= 65) & (buf <= 90), buf | 32, buf)
