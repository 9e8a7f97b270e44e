"""Byte-level BPE by a rank queue: buckets per merge rank, found by find-first-set in a two-level bitmap.

One bit per rank says whether its bucket holds positions; ranks are grouped in words of `WORD` bits, and a summary
word has one bit per non-empty word. The next merge is the lowest set bit of the lowest non-empty word. A bucket holds
left positions in a linked list of symbols; an entry whose pair has changed meanwhile is stale and skipped. The list
holds many pre-tokens one after another, parted by a symbol that pairs with none: pre-tokens do not touch, so one queue
serves them all, and a bucket's positions, merged from the left, are taken at once as arrays where they are many
and one by one where they are few. A pre-token of n bytes costs O(n log n) however long it is, where the scan of all
pairs per merge costs O(n**2).

Cases: a null or empty text has no tokens; a text without white space is one long pre-token or few; repeated rows
and ties give repeated results; an empty table gives an empty result; only doc_id and text are read.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Callable, Iterable
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import map_texts

#: Bits in a word of the bitmap; Python's integers have any length, so summary and words stay of one size up to WORD**2 ranks.
WORD = 512
#: White space as Unicode has it; `regex` counts \x1c-\x1f too, which the reference tokenizer does not.
BLANK = r"\t-\r \x85\xa0  -     　"
#: Blanks other than space and line feed; a text that has one, or has two blanks in a row, is split by the pattern as a whole.
RARE_BLANKS = [c for c in map(chr, [*range(0x09, 0x0E), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]) if c != "\n"]
DOUBLE = ("  ", "\n ", " \n", "\n\n")
#: Bytes that units remembered last may take in a worker, about; as many again are kept of those before.
REMEMBERED = 24 << 20
#: Bytes of pre-tokens that one linked list holds (a longer pre-token has one of its own), and positions of a bucket that are still merged one by one.
LISTED, FEW = 1 << 19, 12


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def splitter(pattern: str):
    """The pre-token pattern with \\s and \\S spelled out, so that both libraries agree on white space."""
    spelled = pattern.replace(r"[^\s\p{L}\p{N}]", rf"[^{BLANK}\p{{L}}\p{{N}}]").replace(r"\S", f"[^{BLANK}]").replace(r"\s", f"[{BLANK}]")
    return regex.compile(spelled)


class Merges:
    """A vocabulary made ready: ids of single bytes, and the rank of every pair of ids that some token splits into."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.single = np.array([ranks[bytes([i])] for i in range(256)], np.int64)
        self.apart = max(ranks.values()) + 1  # the symbol between pre-tokens
        self.pairs: dict[int, int] = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    self.pairs[left << 32 | right] = rank
        order = sorted(self.pairs)
        self.keys = np.array(order, np.int64)
        self.found = np.array([self.pairs[k] for k in order], np.int64)

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, -1 for none."""
        pair = left << 32 | right
        at = np.minimum(np.searchsorted(self.keys, pair), len(self.keys) - 1)
        return np.where(self.keys[at] == pair, self.found[at], -1)


class RankQueue:
    """Positions by the rank of the pair that starts there. `words` and `summary` are the bitmap; a bucket is a list of positions and a list of arrays of them."""

    def __init__(self):
        self.summary, self.words = 0, {}
        self.one: dict[int, list[int]] = {}
        self.many: dict[int, list[np.ndarray]] = {}

    def _mark(self, rank: int) -> None:
        w, bit = divmod(rank, WORD)
        self.words[w] = self.words.get(w, 0) | 1 << bit
        self.summary |= 1 << w

    def push(self, rank: int, at: int) -> None:
        if rank in self.one:
            self.one[rank].append(at)
        else:
            self.one[rank] = [at]
            self._mark(rank)

    def push_all(self, rank: np.ndarray, at: np.ndarray) -> None:
        """at: in ascending order."""
        order = np.argsort(rank, kind="stable")
        rank, at = rank[order], at[order]
        cut = np.flatnonzero(rank[1:] != rank[:-1]) + 1
        ends = [*cut.tolist(), len(rank)]
        begin = 0
        for end in ends:
            r = int(rank[begin])
            if r in self.many:
                self.many[r].append(at[begin:end])
            else:
                self.many[r] = [at[begin:end]]
                self._mark(r)
            begin = end

    def pop(self) -> tuple[int, list[int], list[np.ndarray]]:
        """The least rank with its bucket."""
        w = (self.summary & -self.summary).bit_length() - 1
        word = self.words[w]
        low = word & -word
        self.words[w] = word ^ low
        if word == low:
            self.summary ^= 1 << w
        rank = w * WORD + low.bit_length() - 1
        return rank, self.one.pop(rank, []), self.many.pop(rank, [])


def _once(x: np.ndarray) -> np.ndarray:
    """x sorted, each value once."""
    x.sort()
    return x[np.append(True, x[1:] != x[:-1])]


def _merged(pieces: list[bytes], table: Merges) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all pieces one after another, and n+1 offsets into them; one linked list, one queue."""
    buf = np.frombuffer(b"\0".join(pieces) + b"\0", np.uint8)
    ends = np.cumsum(np.fromiter(map(len, pieces), np.int64, len(pieces)) + 1) - 1
    ids = table.single[buf]
    ids[ends] = table.apart
    n = len(ids)
    after, before = np.arange(1, n + 1), np.arange(-1, n - 1)
    live = np.append(table.rank_of(ids[:-1], ids[1:]), -1)
    gone = np.zeros(n, bool)
    queue = RankQueue()
    at = np.flatnonzero(live >= 0)
    if len(at):
        queue.push_all(live[at], at)
    ids_, after_, before_, live_, gone_ = map(memoryview, (ids, after, before, live, gone))
    get, push = table.pairs.get, queue.push
    while queue.summary:
        rank, one, many = queue.pop()
        if not many and len(one) <= FEW:
            for i in sorted(one) if len(one) > 1 else one:
                if live_[i] != rank:
                    continue
                j = after_[i]
                k = after_[j]  # the symbol between pre-tokens stands at the end, so there always is one
                ids_[i], live_[j], gone_[j], after_[i], before_[k] = rank, -1, True, k, i
                r = get(rank << 32 | ids_[k], -1)
                live_[i] = r
                if r >= 0:
                    push(r, i)
                h = before_[i]
                if h >= 0:
                    r = get(ids_[h] << 32 | rank, -1)
                    if r != live_[h]:  # else the entry that is queued still stands for it
                        live_[h] = r
                        if r >= 0:
                            push(r, h)
            continue
        i = many[0] if len(many) == 1 and not one else _once(np.concatenate([*many, np.array(one, np.int64)]))
        i = i[live[i] == rank]
        if not len(i):
            continue
        j = after[i]
        meets = np.append(False, j[:-1] == i[1:])
        if meets.any():  # of pairs that overlap in a row, every second goes, from the left
            nth = np.arange(len(i))
            i = i[(nth - np.maximum.accumulate(np.where(meets, 0, nth))) % 2 == 0]
            j = after[i]
        k = after[j]
        ids[i], live[j], gone[j], after[i] = rank, -1, True, k
        before[k] = i
        h = before[i]
        h = h[h >= 0]
        changed = _once(np.concatenate([i, h]))
        new = table.rank_of(ids[changed], ids[after[changed]])
        live[changed] = new
        pushed = new >= 0
        if pushed.any():
            queue.push_all(new[pushed], changed[pushed])
    left = ~gone
    left[ends] = False
    upto = np.cumsum(left)
    return ids[left], np.append(0, upto[ends])


def merge_all(pieces: Iterable[bytes], table: Merges) -> list[bytes]:
    """Ids of each pre-token as little-endian 32-bit numbers. A whole pre-token of the vocabulary is its own id."""
    out: list[bytes | None] = []
    held: list[tuple[int, bytes]] = []
    size = 0

    def settle() -> None:
        ids, cut = _merged([p for _, p in held], table)
        raw = ids.astype("<u4").tobytes()
        cut = (cut * 4).tolist()
        for (at, _), a, b in zip(held, cut, cut[1:], strict=False):
            out[at] = raw[a:b]
        held.clear()

    for n, piece in enumerate(pieces):
        whole = table.ranks.get(piece)
        out.append(None if whole is None else whole.to_bytes(4, "little"))
        if whole is None:
            held.append((n, piece))
            size += len(piece)
            if size >= LISTED:
                settle()
                size = 0
    if held:
        settle()
    return out


class Encoder:
    """Ids of whole texts, as little-endian 32-bit numbers. Units between single spaces are remembered with their ids.

    texts: ids of texts; units: ids of units, each a space and then no blanks but single line feeds between others.
    """

    lead = " "  # of every unit, and left out of what is remembered

    def __init__(self, texts: Callable[[list[str]], list[bytes]], units: Callable[[list[str]], list[bytes]] | None = None, most: int = REMEMBERED):
        self.texts, self.units, self.most = texts, units or texts, most
        self.known: dict[str, bytes] = {}  # by the text after the unit's leading space
        self.older: dict[str, bytes] = {}  # what was known before: what is met again comes back, the rest goes
        self.held = 0

    def _learn(self, rests: set[str]) -> None:
        if self.held > self.most:
            self.older, self.known, self.held = self.known, {}, 0
        new = rests.difference(self.known)
        if again := new.intersection(self.older):
            self.known.update((u, self.older[u]) for u in again)
            new -= again
        if new:
            self.known.update(zip(new, self.units([self.lead + u for u in new]), strict=True))  # a set keeps its order while it is not changed
        self.held += sum(map(len, new)) + sum(map(len, again)) + 160 * (len(new) + len(again))  # the heads of three objects and ids

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Where no two blanks touch, every space starts a pre-token, so a text falls apart at its spaces."""
        parts, rests, rest_of = [], set(), []
        for text in texts:
            if any(c in text for c in RARE_BLANKS) or any(c in text for c in DOUBLE):
                parts.append(text)
                rest_of.append(())
            else:
                head, *tail = text.split(" ")
                if tail and (not tail[-1] or tail[-1][-1] == "\n"):  # a blank ends the text
                    head, tail = text, []
                parts.append(head)
                rest_of.append(tail)
                rests.update(tail)
        self._learn(rests)
        heads = self.texts(parts)
        get = self.known.__getitem__
        return [b"".join([head, *map(get, tail)]) for head, tail in zip(heads, rest_of, strict=True)]


def by_queue(ranks: dict[bytes, int], pattern: str) -> Callable[[list[str]], list[bytes]]:
    """Ids of texts by the rank queue: all distinct pre-tokens at once."""
    table, split = Merges(ranks), splitter(pattern)

    def resolve(texts: list[str]) -> list[bytes]:
        pieces = [[t] if t[1:].isalpha() and t[0] == " " else split.findall(t) for t in texts]
        distinct = dict.fromkeys(chain.from_iterable(pieces))
        ids = dict(zip(distinct, merge_all((p.encode("utf-8") for p in distinct), table), strict=True))
        return [b"".join(map(ids.__getitem__, p)) for p in pieces]

    return resolve


class Decoder:
    """Bytes and decimal forms of ids, gathered as arrays."""

    def __init__(self, ranks: dict[bytes, int]):
        most = max(ranks.values()) + 1
        by_id = [b""] * most
        for token, i in ranks.items():
            by_id[i] = token
        self.size = np.fromiter(map(len, by_id), np.int64, most)
        self.begin = np.cumsum(self.size) - self.size
        self.raw = np.frombuffer(b"".join(by_id), np.uint8)
        width = len(str(most)) + 1
        self.digits = np.frombuffer(b"".join(f"{i},".encode().ljust(width, b"\0") for i in range(most)), np.uint8).reshape(most, width)

    def decode(self, ids: np.ndarray) -> bytes:
        size = self.size[ids]
        upto = np.cumsum(size)
        at = np.arange(upto[-1] if len(ids) else 0) + np.repeat(self.begin[ids] - upto + size, size)
        return self.raw[at].tobytes()

    def decimals(self, ids: np.ndarray) -> bytes:
        """The ids in decimal, joined by commas."""
        flat = self.digits[ids].ravel()
        return flat[flat != 0].tobytes()[:-1]


_tools: dict[str, tuple[Encoder, Decoder]] = {}


def tools(path: str, pattern: str) -> tuple[Encoder, Decoder]:
    """One encoder and decoder per vocabulary and worker process."""
    if path not in _tools:
        ranks = load_ranks(path)
        _tools[path] = Encoder(by_queue(ranks, pattern)), Decoder(ranks)
    return _tools[path]


def round_trip(docs: DataFrame, vocabulary: str, pattern: str) -> DataFrame:
    """Per document: doc_id, n_tokens, ids_sha256, decoded_sha256 of its whole text."""

    def fn(batch: pa.RecordBatch):
        enc, dec = tools(vocabulary, pattern)
        n, a, b = [], [], []
        for raw in enc.encode_all([t or "" for t in batch.column(1).to_pylist()]):
            ids = np.frombuffer(raw, "<u4")
            n.append(len(ids))
            a.append(hashlib.sha256(dec.decimals(ids)).hexdigest())
            b.append(hashlib.sha256(dec.decode(ids)).hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return map_texts(docs, ["doc_id", "text"], fn, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
