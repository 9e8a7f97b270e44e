"""Best-fit packing: a configuration linear program over the length histogram, solved by multiplicative weights.

A configuration is a multiset of lengths that fits a sequence. The linear program covers every length's count with as
few configurations as it can; its dual prices come from multiplicative weights, and the best configuration for given
prices from an unbounded knapsack solved by dynamic programming. The weights run until every length is covered, so the
fractional solution is a cover, and any prices divided by their best configuration bound the optimum from below
(`Cover.bound`). Rounding keeps whole runs of the configurations that the earlier part of the cover chose and that leave
next to nothing free; the pieces beyond go by best fit into their slack and into new sequences. How much of the cover is
kept is settled by the number of sequences. Everything on the driver is as large as the histogram (at most
`capacity` lengths), never as the data.

Pieces find their place without a sort: each map task numbers its pieces within a length, a prefix sum over the
tasks' counts makes that a number in the whole table, and a table of ranges (a few per configuration) turns it into
sequence and offset.

Cases: a null or empty text is one piece that holds the end id alone; a longer document is cut into whole-capacity
pieces of which the first is the shorter one; repeated rows and null doc_ids are packed like others; an empty table
gives an empty result; only doc_id and text are read, extra columns are ignored.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections import defaultdict
from collections.abc import Callable
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import bpe
from .common import materialise, slices

CAPACITY, END = 1024, 2
#: Exponent of the weights, the share of a length's count that a round covers at most, and how far below the best price a configuration that runs in a round may be.
STEP, SHARE, NEAR = 1.0, 0.05, 0.002
#: Shares of the tokens covered up to which the cover's configurations may be kept, and how full those must be.
KEPT, FULL = (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.2, 0.1), 0.995

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, nth long"


def knapsack(lengths: np.ndarray, prices: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Greatest price of a configuration by capacity (unbounded knapsack), and the place of the length it takes there, -1 for none. lengths: ascending."""
    best = np.zeros(capacity + 1)
    take = np.full(capacity + 1, -1)
    upto = np.searchsorted(lengths, np.arange(capacity + 1), "right")
    for c in range(1, capacity + 1):
        best[c] = best[c - 1]
        if k := upto[c]:
            value = best[c - lengths[:k]] + prices[:k]
            j = int(value.argmax())
            if value[j] > best[c]:
                best[c], take[c] = value[j], j
    return best, take


def configuration(lengths: np.ndarray, take: np.ndarray, capacity: int, first: int) -> dict[int, int]:
    """Copies by place of a length in the best configuration that holds the length at place `first`."""
    copies = {first: 1}
    c = int(capacity - lengths[first])
    while c > 0:
        if (j := int(take[c])) < 0:
            c -= 1
        else:
            copies[j] = copies.get(j, 0) + 1
            c -= int(lengths[j])
    return copies


Config = tuple[tuple[int, int], ...]  # (length, copies), ascending


@dataclass
class Cover:
    """A fractional solution: runs of configurations, the number of sequences, a lower bound of that number, and the runs made before each of `KEPT`."""

    runs: dict[Config, float]
    value: float
    bound: float
    early: dict[float, dict[Config, float]]


def configuration_lp(lengths: np.ndarray, counts: np.ndarray, capacity: int, step: float = STEP, share: float = SHARE, near: float = NEAR) -> Cover:
    """Configurations and their fractional numbers that cover every length's count.

    A length's price is its share of a sequence, the dual solution of a packing without waste, times its weight, which
    falls exponentially with the share of its count that is covered; a covered length has no price. A round prices
    all configurations at once and runs, of those within `near` of the best, one for each length, until the scarcest of
    its lengths is covered by `share` more. Every round covers some length by `share` or to the end, so there are at most
    len(lengths) / share of them.
    """
    cover = np.zeros(len(lengths))
    total = float((lengths * counts).sum())
    out = Cover({}, 0.0, total / capacity, {})
    while len(open_ := np.flatnonzero(cover < 1 - 1e-9)):
        done = float((cover * lengths * counts).sum()) / total
        out.early.update((k, dict(out.runs)) for k in KEPT if done >= k and k not in out.early)
        n, c = lengths[open_], cover[open_]
        prices = n / capacity * np.exp(-step * (c - c.min()))
        best, take = knapsack(n, prices, capacity)
        out.bound = max(out.bound, float((prices * counts[open_]).sum() / best[capacity]))
        value = prices + best[capacity - n]
        gained = np.zeros(len(n))
        for i in np.argsort(-value, kind="stable").tolist():
            if value[i] < best[capacity] * (1 - near):
                break
            if gained[i] >= share:
                continue
            copies = configuration(n, take, capacity, i)
            at, k = np.fromiter(copies, np.int64), np.fromiter(copies.values(), float)
            of = counts[open_[at]]
            run = float((np.minimum(share, 1 - cover[open_[at]]) * of / k).min())
            if run <= 0:
                continue
            gain = k * run / of
            cover[open_[at]] += gain
            gained[at] += gain
            key = tuple(sorted(zip(n[at].tolist(), k.astype(int).tolist(), strict=True)))
            out.runs[key] = out.runs.get(key, 0.0) + run
            out.value += run
    return out


@dataclass
class Plan:
    """Ranges of ranks by length: rank r of a length lies in sequence base + (r - low) // copies at offset + copy * length."""

    capacity: int
    sequences: int
    ranges: dict[int, np.ndarray]  # columns low, base, copies, offset

    def place(self, lengths: np.ndarray, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        seq, off = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
        for n in np.unique(lengths):
            at = np.flatnonzero(lengths == n)
            table = self.ranges[int(n)]
            row = table[np.searchsorted(table[:, 0], ranks[at], "right") - 1]
            k = ranks[at] - row[:, 0]
            seq[at] = row[:, 1] + k // row[:, 2]
            off[at] = row[:, 3] + k % row[:, 2] * n
        return seq, off


def best_fit(groups: list[tuple[dict[int, int], int]], left: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Pieces by falling length into the fullest sequence that has room; equal sequences move together, so the work follows the histogram."""
    room: dict[int, list[tuple[dict[int, int], int]]] = defaultdict(list)
    for config, times in groups:
        if times:
            room[capacity - sum(n * k for n, k in config.items())].append((config, times))
    for n in sorted(left, reverse=True):
        need = left[n]
        while need > 0:
            free = min((r for r, g in room.items() if r >= n and g), default=None)
            if free is None:
                room[capacity].append(({}, max(1, need // (capacity // n))))
                continue
            config, times = room[free].pop()
            each = min(free // n, need)
            taken = min(times, need // each)
            if times > taken:
                room[free].append((config, times - taken))
            grown = dict(config)
            grown[n] = grown.get(n, 0) + each
            room[free - each * n].append((grown, taken))
            need -= taken * each
    return [x for g in room.values() for x in g if x[0]]


def rounded(runs: dict[Config, float], histogram: dict[int, int], capacity: int, full: float = FULL) -> tuple[list[tuple[dict[int, int], int]], dict[int, int]]:
    """Whole runs of the configurations that leave next to nothing free, and the pieces beyond them by length."""
    left, groups = dict(histogram), []
    for key, x in sorted(runs.items(), key=lambda r: (-r[1], r[0])):
        if sum(n * k for n, k in key) >= full * capacity:
            times = min(int(x + 1e-6), *(left[n] // k for n, k in key))
            if times > 0:
                groups.append((dict(key), times))
                for n, k in key:
                    left[n] -= k * times
    return groups, {n: c for n, c in left.items() if c}


def choose(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[dict[int, int], int]], Cover]:
    """Sequences by kind, and the linear program's cover: of the parts of it that may be kept, the one that ends in the fewest sequences."""
    lengths = np.array(sorted(histogram), np.int64)
    cover = configuration_lp(lengths, np.array([histogram[int(n)] for n in lengths], np.int64), capacity)
    tried = []
    for k in KEPT:
        groups, left = rounded(cover.early.get(k, cover.runs), histogram, capacity)
        tried.append(best_fit(groups, left, capacity))
    return min(tried, key=lambda groups: sum(times for _, times in groups)), cover  # the first of equals keeps most


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """Linear program, rounding, best fit; counts stay whole throughout."""
    groups = choose(histogram, capacity)[0] if histogram else []
    low: dict[int, int] = defaultdict(int)
    ranges: dict[int, list] = defaultdict(list)
    base = 0
    for config, times in groups:
        at = 0
        for n in sorted(config, reverse=True):
            ranges[n].append((low[n], base, config[n], at))
            low[n] += config[n] * times
            at += config[n] * n
        base += times
    return Plan(capacity, base, {n: np.array(r, np.int64) for n, r in ranges.items()})


#: Units in a string that is encoded at once.
JOINED = 64
#: The byte-level pre-tokenizer whose pre-tokens `PLAIN` finds, as the vocabulary's file describes it.
BYTE_LEVEL = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": True}
#: Latin letters; marks, but for the apostrophe.
LETTERS, MARKS = "A-Za-z\xc0-\xd6\xd8-\xf6\xf8-\u024f", "!-&(-/:-@\\[-`{-~\xa1-\xa9\xab\xac\xae-\xb1\xb4\xb6-\xb8\xbb\xbf\xd7\xf7"
#: Pre-tokens of these and of ASCII digits where no two blanks touch; any other character alone.
PLAIN = re.compile(rf"'(?:[stmd]|re|ve|ll)| ?[{LETTERS}]+| ?[0-9]+| ?[{MARKS}']+|\n|[\0-\U0010ffff]")
PLAIN_ALONE = re.compile(rf"[{LETTERS}0-9{MARKS}'\n]")


def byte_characters() -> dict[int, str]:
    """The character that stands for each byte in a byte-level vocabulary: itself where it is printed, else one of those from U+0100 on."""
    printed = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    others = (b for b in range(256) if b not in printed)
    return {b: chr(b) for b in printed} | {b: chr(256 + n) for n, b in enumerate(others)}


class PreTokens(bpe.Encoder):
    """Texts of plain characters fall apart into pre-tokens, which are remembered with their ids; other texts go to `others`."""

    lead = ""

    def __init__(self, words: Callable[[list[str]], list[bytes]], others: bpe.Encoder, most: int = bpe.REMEMBERED):
        super().__init__(words, most=most)
        self.others = others

    def encode_all(self, texts: list[str]) -> list[bytes]:
        cut: list[list[str] | None] = []
        distinct: set[str] = set()
        for text in texts:
            plain = text[-1:] not in (" ", "\n") and not any(c in text for c in bpe.RARE_BLANKS) and not any(c in text for c in bpe.DOUBLE)
            cut.append(PLAIN.findall(text) if plain else None)
            distinct.update(cut[-1] or ())
        if odd := {p for p in distinct if len(p) == 1 and not PLAIN_ALONE.match(p)}:
            cut = [None if c is None or not odd.isdisjoint(c) else c for c in cut]
            distinct -= odd
        self._learn(distinct)
        get = self.known.__getitem__
        rest = iter(self.others.encode_all([t for t, c in zip(texts, cut, strict=True) if c is None]))
        return [next(rest) if c is None else b"".join(map(get, c)) for c in cut]


def by_tokenizers(path: str) -> tuple[Callable[[list[str]], list[bytes]], Callable[[list[str]], list[bytes]], Callable[[list[str]], list[bytes]] | None]:
    """Ids by `tokenizers`: of any texts; of units (a space, then no blanks but single line feeds) many at a time, parted by line feeds, which
    are ids of their own there; and of pre-tokens that `PLAIN` finds, by the library's model alone (None: the vocabulary splits texts otherwise)."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
    encode = tokenizer.encode_batch_fast
    line = encode(["\n"], add_special_tokens=False)[0].ids[0]
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    characters, tokenize = byte_characters(), tokenizer.model.tokenize
    raw = [i.to_bytes(4, "little") for i in range(max(tokenizer.get_vocab().values()) + 1)]

    def texts(parts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in encode(parts, add_special_tokens=False)]

    def units(parts: list[str]) -> list[bytes]:
        out: list[bytes] = []
        for a in range(0, len(parts), JOINED):
            joined = "\n".join(parts[a : a + JOINED])
            got = np.array(encode([joined + "\n"], add_special_tokens=False)[0].ids, "<u4")
            ends = np.flatnonzero(got == line)
            if len(ends) > JOINED or a + JOINED > len(parts):  # line feeds inside units do not end them
                ends = ends[np.cumsum([p.count("\n") + 1 for p in parts[a : a + JOINED]]) - 1]
            raw, ends = got.tobytes(), (4 * ends).tolist()
            out += [raw[b:e] for b, e in zip([0, *(e + 4 for e in ends[:-1])], ends, strict=True)]
        return out

    def words(parts: list[str]) -> list[bytes]:
        mapped = "\0".join(parts).encode().decode("latin-1").translate(characters).split(characters[0])
        return [b"".join([raw[t.id] for t in tokenize(w)]) for w in mapped] if parts else []

    known = told["pre_tokenizer"] == BYTE_LEVEL and told["normalizer"] is None and all(a["special"] for a in told["added_tokens"])
    return texts, units, words if known else None


_packers: dict[str, bpe.Encoder] = {}


def _packer(path: str) -> bpe.Encoder:
    if path not in _packers:
        texts, units, words = by_tokenizers(path)
        plain = bpe.Encoder(texts, units)
        _packers[path] = plain if words is None else PreTokens(words, plain)
    return _packers[path]


def pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """One row per piece, with the task that made it and its number there among pieces of its length. vocabulary: a file for `tokenizers`."""
    names = [k.split()[0] for k in PIECES.split(", ")]
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
    last = end.to_bytes(4, "little")

    def run(batches):
        enc = _packer(vocabulary)
        task = TaskContext.get().partitionId()
        seen: dict[int, int] = defaultdict(int)
        for part in (p for batch in batches for p in slices(batch, "text", 2 << 20)):
            cols: list[list] = [[] for _ in names]
            for doc, raw in zip(part.column(0).to_pylist(), enc.encode_all([t or "" for t in part.column(1).to_pylist()]), strict=True):
                raw += last
                n = len(raw) // 4
                first = n - (n - 1) // capacity * capacity
                for piece, (a, b) in enumerate(zip(chain([0], range(first, n, capacity)), range(first, n + 1, capacity), strict=True)):
                    for col, value in zip(cols, (doc, piece, a, b - a, zlib.crc32(raw[4 * a : 4 * b]), task, seen[b - a]), strict=True):
                        col.append(value)
                    seen[b - a] += 1
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, kinds, strict=True)], names)

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    made = materialise(pieces(docs, vocabulary, capacity, end), "pieces")
    counts = materialise(made.groupBy("task", "length").agg(F.count(F.lit(1)).alias("n")), "counts")
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    layout = spark.sparkContext.broadcast(plan(histogram, capacity))
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    ranked = made.join(starts.hint("merge"), ["task", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("nth")).alias("rank"))

    def place(batches):
        for b in batches:
            seq, off = layout.value.place(b.column(3).to_numpy(), b.column(5).to_numpy())
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(seq), pa.array(off)], [*b.schema.names[:5], "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
