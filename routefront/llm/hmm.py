"""Language-model scoring by a hidden Markov model over words.

Training counts every word of all training documents (a shuffle of distinct words a task). The `SYMBOLS_WORDS` most
frequent words are symbols of their own, all others share `CLASSES` symbols by their ending; P(word | symbol) of a shared
symbol is its smoothed share of the symbol's count. Every text is read once more and written as its symbols; latent states
start from Baum-Welch on a bounded sample of whole texts and are re-estimated by full passes in which every task sends its
expected counts for all its training documents, however long. A text's score is the scaled forward recursion over its
symbols and the end, plus log P(word | symbol): the exact log-likelihood.

Word counts reach the texts in two ways: the most frequent words, `KNOWN_WORDS` at most, are broadcast (found by levels of
counts, so no sort of the vocabulary meets in one place), and all others, each a small share of all tokens, are joined by a
shuffle, summed within each document before it.

Cases: a null or empty text has one token, the end; a null doc_id is not learnt from and not held out; repeated rows
are scored each; without training documents counts are 0 and the model is uniform; an empty table gives an empty result;
only doc_id and text are read.
"""

from __future__ import annotations

import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_bucket, materialise, slices

STATES, SYMBOLS_WORDS, CLASSES, KNOWN_WORDS = 8, 4096, 64, 150_000
#: Documents of the sample that starts the states, passes over it, passes over all training documents.
SAMPLE_DOCS, SAMPLE_PASSES, PASSES = 300, 12, 3
#: Symbols that a task holds so that texts of like length run together, and that run at once (a longer text runs alone).
GATHERED, RUN = 6_000_000, 1_000_000
END = b""
#: Distinct words a task holds before it sends their counts.
HELD = 400_000


def tokens(text: str | None) -> list[bytes]:
    """Words with A-Z lowered, then the end."""
    out = (text or "").encode().lower().split()
    out.append(END)
    return out


def class_of(word: bytes) -> int:
    return zlib.crc32(word[-2:]) % CLASSES


@dataclass
class Model:
    start: np.ndarray  # (states,)
    move: np.ndarray  # (states, states)
    emit: np.ndarray  # (symbols, states)

    @staticmethod
    def random(symbols: int, weights: np.ndarray, seed: int = 3) -> Model:
        r = np.random.default_rng(seed)
        emit = (weights[:, None] + 1.0) * r.uniform(0.2, 1.8, (symbols, STATES))
        move = r.uniform(0.5, 1.5, (STATES, STATES)) + 3.0 * STATES * np.eye(STATES)  # states that last find topics and languages
        return Model(np.full(STATES, 1 / STATES), move / move.sum(1, keepdims=True), emit / emit.sum(0))


class Sequences:
    """Symbol sequences, longest first, laid out by time: what all sequences have at a time stands together."""

    def __init__(self, parts: list[np.ndarray]):
        self.order = sorted(range(len(parts)), key=lambda i: -len(parts[i]))
        length = np.array([len(parts[i]) for i in self.order], np.int64)
        self.live = np.searchsorted(-length, -np.arange(length.max(initial=0)), "left")  # sequences longer than t
        self.begin = np.append(0, np.cumsum(self.live))
        flat = np.concatenate([np.zeros(0, np.int64), *(parts[i] for i in self.order)]).astype(np.int64)
        time = np.arange(len(flat)) - np.repeat(np.cumsum(length) - length, length)
        which = np.repeat(np.arange(len(length)), length)
        self.symbols = np.empty(len(flat), np.int64)
        self.symbols[self.begin[time] + which] = flat
        self.times = [(t, int(a), int(a + k), int(k)) for t, (a, k) in enumerate(zip(self.begin[:-1], self.live, strict=True))]

    def _scaled(self, m: Model, keep: bool) -> tuple[np.ndarray | None, np.ndarray]:
        """Scaled states (if kept) and scales by time."""
        alphas = np.empty((len(self.symbols), STATES)) if keep else None
        scales = np.empty(len(self.symbols))
        alpha = None
        for t, a, b, k in self.times:
            alpha = m.emit[self.symbols[a:b]] * (m.start if t == 0 else alpha[:k] @ m.move)
            scales[a:b] = c = alpha.sum(1)
            alpha /= c[:, None]
            if keep:
                alphas[a:b] = alpha
        return alphas, scales

    def _sums(self, scales: np.ndarray) -> np.ndarray:
        which = np.arange(len(scales)) - np.repeat(self.begin[:-1], self.live)
        return np.bincount(which, np.log(scales), len(self.order))

    def likelihoods(self, m: Model) -> np.ndarray:
        """Log-likelihood (natural) of each sequence, in the order given."""
        out = np.empty(len(self.order))
        out[self.order] = self._sums(self._scaled(m, False)[1])
        return out

    def expected(self, m: Model) -> tuple[float, np.ndarray, np.ndarray, np.ndarray]:
        """Log-likelihood and expected counts of starts, moves and emissions (Baum-Welch)."""
        alphas, scales = self._scaled(m, True)
        moves = np.zeros((STATES, STATES))
        beta = np.ones((len(self.order), STATES))
        for t, a, b, k in reversed(self.times[1:]):
            out = m.emit[self.symbols[a:b]] * beta[:k]
            out /= scales[a:b, None]
            before = self.times[t - 1][1]
            moves += alphas[before : before + k].T @ out
            alphas[a:b] *= beta[:k]  # now the states given the whole sequence
            beta[:k] = out @ m.move.T
        moves *= m.move
        alphas[: len(beta)] *= beta
        emits = np.stack([np.bincount(self.symbols, alphas[:, s], len(m.emit)) for s in range(STATES)], axis=1)
        return float(np.log(scales).sum()), alphas[: len(beta)].sum(0), moves, emits


def runs(parts: list[np.ndarray]) -> list[list[int]]:
    """Places of sequences that run together: of like length, `RUN` symbols at most unless one alone is longer."""
    out, size = [], RUN
    for i in sorted(range(len(parts)), key=lambda i: -len(parts[i])):
        if size + len(parts[i]) > RUN:
            out.append([])
            size = 0
        out[-1].append(i)
        size += len(parts[i])
    return out


def estimate(starts: np.ndarray, moves: np.ndarray, emits: np.ndarray) -> Model:
    """Model from expected counts; a little is added so that no symbol becomes impossible."""
    moves, emits = moves + 0.1, emits + 0.01
    return Model((starts + 0.1) / (starts + 0.1).sum(), moves / moves.sum(1, keepdims=True), emits / emits.sum(0))


def word_counts(docs: DataFrame) -> DataFrame:
    """word (binary, lowered), n: counts over all rows of docs; the end counts once a document."""

    def run(batches):
        held: Counter = Counter()

        def send():
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], ["word", "n"])
            held.clear()

        for batch in batches:
            for text in batch.column(0):
                held.update(tokens(text.as_py()))
                if len(held) > HELD:
                    yield from send()
        if held:
            yield from send()

    return docs.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


@dataclass
class Vocabulary:
    """Fixed numbers of the corpus, and what is broadcast: counts of the most frequent words, symbols of the first of them."""

    total: int  # tokens
    distinct: int
    counts: dict[bytes, int]
    symbol: dict[bytes, int]
    class_total: np.ndarray
    class_distinct: np.ndarray

    def __len__(self) -> int:
        return SYMBOLS_WORDS + CLASSES

    def within(self, word: bytes, n: int) -> float:
        """log10 P(word | its shared symbol)."""
        k = class_of(word)
        return float(np.log10((n + 0.5) / (self.class_total[k] + 0.5 * (self.class_distinct[k] + 1))))


def _least_level(counts: DataFrame, level) -> int:
    """The least level of counts (64 levels for each doubling) from which on there are at most KNOWN_WORDS words."""
    per = sorted(((r["level"], r["words"]) for r in counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("words")).collect()), reverse=True)
    words, least = 0, 1 << 30
    for at, n in per:  # a few thousand levels at most
        words += n
        if words > KNOWN_WORDS:
            break
        least = at
    return least


def vocabulary(counts: DataFrame) -> Vocabulary:
    level = F.floor(F.log2("n") * 64).cast("int")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("t"), F.count(F.lit(1)).alias("d")).first()
    top = [(bytes(r["word"]), r["n"]) for r in counts.where(level >= _least_level(counts, level)).collect()]  # at most KNOWN_WORDS
    top.sort(key=lambda x: (-x[1], x[0]))
    symbol = {w: i for i, (w, _) in enumerate(top[:SYMBOLS_WORDS])}
    ending = F.when(F.length("word") > 2, F.substring(F.col("word"), -2, 2)).otherwise(F.col("word"))
    per_class = counts.groupBy((F.crc32(ending) % CLASSES).cast("int").alias("k")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("d"))
    class_total, class_distinct = np.zeros(CLASSES), np.zeros(CLASSES)
    for r in per_class.collect():
        class_total[r["k"]], class_distinct[r["k"]] = r["n"], r["d"]
    for w, n in top[:SYMBOLS_WORDS]:  # these have symbols of their own
        class_total[class_of(w)] -= n
        class_distinct[class_of(w)] -= 1
    return Vocabulary(total["t"], total["d"], dict(top), symbol, class_total, class_distinct)


def _expected_counts(texts: DataFrame, symbols: int, model) -> DataFrame:
    """Summed expected counts by row: -2 the log-likelihood, -1 starts, 0.. moves by state, then emissions by symbol. texts: column symbols."""

    def run(batches):
        m = model.value
        ll, starts, moves, emits = 0.0, np.zeros(STATES), np.zeros((STATES, STATES)), np.zeros((symbols, STATES))

        def add(parts):
            nonlocal ll
            for group in runs(parts):
                got = Sequences([parts[i] for i in group]).expected(m)
                ll += got[0]
                for have, more in zip((starts, moves, emits), got[1:], strict=True):
                    have += more

        parts, size = [], 0
        for batch in batches:
            for s in batch.column(0):
                parts.append(np.frombuffer(s.as_py(), np.uint16))
                size += len(parts[-1])
                if size > GATHERED:
                    add(parts)
                    parts, size = [], 0
        add(parts)
        used = np.flatnonzero(emits.any(axis=1))
        key = np.concatenate([[-2, -1], np.arange(STATES), STATES + used])
        rows = np.vstack([np.full(STATES, ll), starts, moves, emits[used]])
        yield pa.RecordBatch.from_arrays([pa.array(key.astype(np.int32)), *(pa.array(rows[:, i].copy()) for i in range(STATES))], ["row", *(f"s{i}" for i in range(STATES))])

    schema = "row int, " + ", ".join(f"s{i} double" for i in range(STATES))
    return texts.select("symbols").mapInArrow(run, schema).groupBy("row").agg(*(F.sum(f"s{i}").alias(f"s{i}") for i in range(STATES)))


def baum_welch(texts: DataFrame, symbols: int, model: Model, passes: int = PASSES) -> tuple[Model, list[float]]:
    """Re-estimation over all rows of texts; what comes back has a row per state and symbol, whatever the input. Also the log-likelihood before each pass."""
    spark, history = texts.sparkSession, []
    for _ in range(passes):
        shared = spark.sparkContext.broadcast(model)
        starts, moves, emits = np.zeros(STATES), np.zeros((STATES, STATES)), np.zeros((symbols, STATES))
        for r in _expected_counts(texts, symbols, shared).collect():
            row = np.array(r[1:])
            if r["row"] == -2:
                history.append(float(row[0]))
            elif r["row"] == -1:
                starts = row
            elif r["row"] < STATES:
                moves[r["row"]] = row
            else:
                emits[r["row"] - STATES] = row
        model = estimate(starts, moves, emits)
    return model, history


def first_model(texts: DataFrame, vocab: Vocabulary) -> Model:
    """States from Baum-Welch on `SAMPLE_DOCS` whole texts, the first by hash of the id, on the driver."""
    weights = np.zeros(len(vocab))
    for w, i in vocab.symbol.items():
        weights[i] = vocab.counts[w]
    weights[SYMBOLS_WORDS:] = np.maximum(vocab.class_total, 0)
    model = Model.random(len(vocab), weights / max(1.0, weights.sum()) * 1e4)
    rows = texts.orderBy(F.xxhash64("doc_id"), "doc_id", "symbols").limit(SAMPLE_DOCS).select("symbols").collect()
    if rows:
        seqs = Sequences([np.frombuffer(r["symbols"], np.uint16) for r in rows])
        for _ in range(SAMPLE_PASSES):
            _, *counts = seqs.expected(model)
            counts[2] += 0.05 * weights[:, None] / max(1.0, weights.sum()) * counts[2].sum() / STATES  # symbols the sample lacks
            model = estimate(*counts)
    return model


READ = "row long, doc_id long, held_out boolean, learn boolean, n_tokens long, known long, base double, inner double, symbols binary, word binary, times int"


def _read(docs: DataFrame, vocab) -> DataFrame:
    """A row per document (word null) with its symbols and what broadcast counts settle, and a row per distinct other word of it."""
    names = [c.split()[0] for c in READ.split(", ")]
    kinds = (pa.int64(), pa.int64(), pa.bool_(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.binary(), pa.int32())

    def run(batches):
        v = vocab.value
        place = {w: i for i, w in enumerate(v.counts)}
        n = np.fromiter(v.counts.values(), float, len(place))
        base = np.log10(n + 0.5) - np.log10(v.total + 0.5 * (v.distinct + 1))
        inner = np.fromiter((0.0 if w in v.symbol else v.within(w, c) for w, c in v.counts.items()), float, len(place))
        symbol = np.fromiter((v.symbol.get(w, SYMBOLS_WORDS + class_of(w)) for w in place), np.int64, len(place))
        base, inner, symbol = np.append(base, 0.0), np.append(inner, 0.0), np.append(symbol, 0).astype(np.uint16)  # the last for words not known here
        get = place.get
        task, k = TaskContext.get().partitionId() << 33, 0
        for part in (p for batch in batches for p in slices(batch, "text", 2 << 20)):
            cols: list[list] = [[] for _ in names]
            for doc, held, learn, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True):
                words = tokens(text)
                at = np.array([get(w, -1) for w in words])
                seen = symbol[at]
                missing = np.flatnonzero(at < 0).tolist()
                other = [words[i] for i in missing]
                if other:
                    seen[missing] = [SYMBOLS_WORDS + class_of(w) for w in other]
                row = task + k
                k += 1
                rows = [(row, doc, held, learn, len(words), len(words) - len(other), float(base[at].sum()), float(inner[at].sum()), seen.tobytes(), None, None)]
                rows += [(row, *(None,) * 8, w, c) for w, c in Counter(other).items()]
                for col, values in zip(cols, zip(*rows, strict=True), strict=True):
                    col += values
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

    return docs.select("doc_id", "held_out", "learn", "text").mapInArrow(run, READ)


def _likelihoods(texts: DataFrame, model) -> DataFrame:
    """texts with `hmm`, log10 of the likelihood of the symbols, in place of them."""
    schema = "row long, doc_id long, held_out boolean, n_tokens long, known long, base double, hmm double"

    def run(batches):
        for batch in batches:
            parts = [np.frombuffer(s.as_py(), np.uint16) for s in batch.column(7)]
            ll = np.empty(len(parts))
            for group in runs(parts):
                ll[group] = Sequences([parts[i] for i in group]).likelihoods(model.value)
            hmm = ll / np.log(10) + batch.column(6).to_numpy()
            yield pa.RecordBatch.from_arrays([*batch.columns[:6], pa.array(hmm)], [c.split()[0] for c in schema.split(", ")])

    return texts.select("row", "doc_id", "held_out", "n_tokens", "known", "base", "inner", "symbols").mapInArrow(run, schema)


def score(docs: DataFrame, passes: int = PASSES) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    spark = docs.sparkSession
    rows = docs.select("doc_id", "text", F.coalesce(id_bucket("doc_id", 5) == 1, F.lit(False)).alias("held_out"), F.coalesce(id_bucket("doc_id", 5) != 1, F.lit(False)).alias("learn"))
    counts = materialise(word_counts(rows.where("learn")), "words")
    v = vocabulary(counts)
    made = materialise(_read(rows, spark.sparkContext.broadcast(v)), "read")
    whole, other = made.where(F.col("word").isNull()), made.where(F.col("word").isNotNull()).select("row", "word", "times")
    learn = whole.where("learn").select("doc_id", "symbols")
    model, _ = baum_welch(learn, len(v), first_model(learn, v), passes)
    scored = _likelihoods(whole, spark.sparkContext.broadcast(model))
    scale = F.lit(float(np.log10(v.total + 0.5 * (v.distinct + 1))))
    ending = F.when(F.length("word") > 2, F.substring(F.col("word"), -2, 2)).otherwise(F.col("word"))
    inner = F.element_at(F.array(*(F.lit(float(np.log10(max(t, 0) + 0.5 * (d + 1)))) for t, d in zip(v.class_total, v.class_distinct, strict=True))), (F.crc32(ending) % CLASSES + 1).cast("int"))
    found = other.join(counts, "word", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    log = F.log10(F.col("n") + F.lit(0.5))
    sums = found.groupBy("row").agg(F.sum(F.col("times") * (log - scale)).alias("base2"), F.sum(F.col("times") * (log - inner)).alias("hmm2"), F.sum(F.when(F.col("n") > 0, F.col("times")).otherwise(0)).alias("known2"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    return scored.join(sums, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + zero("known2")).cast("long").alias("n_known"), F.lit(v.total).cast("long").alias("train_tokens"), (F.col("base") + zero("base2")).alias("base_score"), (F.col("hmm") + zero("hmm2")).alias("score")
    )
