"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads a text's words byte by byte in both directions and labels every byte position; a document's
probability of a language is the mean over all its positions. Its state starts anew at each word (and every `SPAN` bytes
of a longer one), so equal words get equal labels and a worker needs to run each distinct word once; the pooled
sum over all positions of the whole text is unchanged by that. Weights are trained in numpy by backpropagation through
time (Adam) on words of a bounded sample of documents: `DOCS_PER_LANGUAGE` by hash of the id, `WORDS_PER_DOC` evenly
spaced words each.

Cases: a null text, or one without any letter, is `und` with score 0; ties go to the alphabetically first language;
a table without usable languages gives `und` for all; repeated rows are judged each; an empty table gives an empty
result; only doc_id, text and (for training) lang are read.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_bucket, map_texts

HIDDEN, SPAN = 16, 24
DOCS_PER_LANGUAGE, WORDS_PER_DOC, STEPS, BATCH = 300, 60, 300, 384
#: Distinct words whose labels a worker remembers.
REMEMBERED = 200_000

_LETTER = regex.compile(r"\p{L}")


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def matrix(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Words as a byte matrix padded with zeros, and their lengths (at most SPAN)."""
    n = np.fromiter(map(len, words), np.int64, len(words))
    width = int(n.max(initial=1))
    flat = np.frombuffer(b"".join(w.ljust(width, b"\0") for w in words), np.uint8)
    return flat.reshape(len(words), width), n


@dataclass
class Network:
    """Per direction: input table (256, 3h), recurrent weights (h, 3h), bias (3h); output (2h, languages) and bias."""

    languages: list[str]
    table: list[np.ndarray]
    recur: list[np.ndarray]
    bias: list[np.ndarray]
    out: np.ndarray
    out_bias: np.ndarray

    @staticmethod
    def start(languages: list[str], hidden: int = HIDDEN, seed: int = 11) -> Network:
        r = np.random.default_rng(seed)
        draw = lambda *s: (r.standard_normal(s) / np.sqrt(hidden)).astype(np.float32)
        return Network(languages, [draw(256, 3 * hidden) for _ in "ab"], [draw(hidden, 3 * hidden) for _ in "ab"], [np.zeros(3 * hidden, np.float32) for _ in "ab"], draw(2 * hidden, len(languages)), np.zeros(len(languages), np.float32))

    def parameters(self) -> list[np.ndarray]:
        return [*self.table, *self.recur, *self.bias, self.out, self.out_bias]

    def _run(self, d: int, x: np.ndarray, n: np.ndarray, tape: list | None = None) -> np.ndarray:
        """States of one direction at every position (time, word, hidden); padding leaves the state as it is."""
        h = self.recur[d].shape[0]
        state = np.zeros((len(x), h), np.float32)
        states = np.zeros((x.shape[1], len(x), h), np.float32)
        for t in range(x.shape[1]) if d == 0 else range(x.shape[1] - 1, -1, -1):
            live = (n > t)[:, None]
            a = self.table[d][x[:, t]] + self.bias[d]
            b = state @ self.recur[d]
            z = _sigmoid(a[:, :h] + b[:, :h])
            r = _sigmoid(a[:, h : 2 * h] + b[:, h : 2 * h])
            c = np.tanh(a[:, 2 * h :] + r * b[:, 2 * h :])
            new = np.where(live, (1 - z) * state + z * c, state)
            if tape is not None:
                tape.append((t, live, state, z, r, c, b[:, 2 * h :]))
            state = states[t] = new
        return states

    def probabilities(self, x: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Language probabilities at every position (time, word, language); padding counts nothing."""
        s = np.concatenate([self._run(0, x, n), self._run(1, x, n)], axis=2)
        y = s @ self.out + self.out_bias
        y = np.exp(y - y.max(axis=2, keepdims=True))
        y /= y.sum(axis=2, keepdims=True)
        return y * (n[None, :] > np.arange(x.shape[1])[:, None])[:, :, None]

    def gradients(self, x: np.ndarray, n: np.ndarray, y: np.ndarray) -> tuple[float, list[np.ndarray]]:
        """Mean cross entropy over all positions and its gradients, by backpropagation through time."""
        h = self.recur[0].shape[0]
        tapes: list[list] = [[], []]
        s = np.concatenate([self._run(d, x, n, tapes[d]) for d in (0, 1)], axis=2)
        logits = s @ self.out + self.out_bias
        logits -= logits.max(axis=2, keepdims=True)
        p = np.exp(logits)
        p /= p.sum(axis=2, keepdims=True)
        mask = (n[None, :] > np.arange(x.shape[1])[:, None]).astype(np.float32) / n.sum()
        rows = np.arange(len(y))
        loss = float(-(np.log(p[:, rows, y] + 1e-9) * mask).sum())
        p[:, rows, y] -= 1
        p *= mask[:, :, None]
        g_out = np.einsum("tbh,tbl->hl", s, p)
        ds = p @ self.out.T
        g_table, g_recur, g_bias = [], [], []
        for d in (0, 1):
            gt, gr, gb = np.zeros_like(self.table[d]), np.zeros_like(self.recur[d]), np.zeros_like(self.bias[d])
            back = np.zeros((len(x), h), np.float32)
            u = self.recur[d]
            for t, live, state, z, r, c, bc in reversed(tapes[d]):
                total = back + ds[t, :, d * h : (d + 1) * h] * live
                on = total * live
                dz = on * (c - state) * z * (1 - z)
                dc = on * z * (1 - c * c)
                dr = dc * bc * r * (1 - r)
                da = np.concatenate([dz, dr, dc], axis=1)
                db = np.concatenate([dz, dr, dc * r], axis=1)
                np.add.at(gt, x[:, t], da)
                gb += da.sum(axis=0)
                gr += state.T @ db
                back = np.where(live, on * (1 - z), total) + db @ u.T
            g_table.append(gt)
            g_recur.append(gr)
            g_bias.append(gb)
        return loss, [*g_table, *g_recur, *g_bias, g_out, p.sum(axis=(0, 1))]


def train(words: list[bytes], labels: np.ndarray, languages: list[str], steps: int = STEPS, batch: int = BATCH, rate: float = 0.02, seed: int = 5) -> Network:
    net = Network.start(languages)
    if not words:
        return net
    r = np.random.default_rng(seed)
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in net.parameters()]
    places = [np.flatnonzero(labels == i) for i in range(len(languages))]
    for step in range(1, steps + 1):
        pick = np.concatenate([r.choice(p, batch // len(languages) + 1) for p in places])  # languages in equal shares
        x, n = matrix([words[i] for i in pick])
        _, grads = net.gradients(x, n, labels[pick])
        fade = rate * (1 - step / (steps + 1)) ** 0.5
        for p, g, (m, v) in zip(net.parameters(), grads, moments, strict=True):
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            p -= (fade * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
    return net


def spans(word: bytes) -> list[bytes]:
    return [word[i : i + SPAN] for i in range(0, len(word), SPAN)] if len(word) > SPAN else [word]


def fit(docs: DataFrame, learn: Column, per_language: int = DOCS_PER_LANGUAGE, words_per_doc: int = WORDS_PER_DOC) -> Network:
    """Network from documents for which `learn` holds and lang is known; the sample is the same for the same documents."""
    known = docs.select("doc_id", "text", "lang").where(learn & F.col("lang").isNotNull() & F.col("text").isNotNull())
    have = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a language
    share = F.lit(0.0)
    for lang, n in have.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, 2 * per_language / n))).otherwise(share)
    order = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)).cast("long")
    sample = known.withColumn("ord", order).where(F.col("ord") < share * (1 << 20)).select("doc_id", "text", "lang", "ord")

    def fn(batch: pa.RecordBatch):
        out = []
        for text in batch.column(1).to_pylist():
            w = text.encode().split()
            few = min(words_per_doc, len(w))
            out.append([s for i in range(few) for s in spans(w[i * len(w) // few])])
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array(out, pa.list_(pa.binary()))], ["doc_id", "lang", "ord", "words"])

    rows = map_texts(sample, ["doc_id", "text", "lang", "ord"], fn, "doc_id long, lang string, ord long, words array<binary>")
    rows = rows.orderBy("ord", "doc_id", "words").limit(4 * per_language * len(have)).collect() if have else []  # about half as many, unless ids repeat
    rows.sort(key=lambda r: (r["lang"], r["ord"], r["doc_id"]))
    languages = sorted({r["lang"] for r in rows if r["words"]})
    words, labels, taken = [], [], Counter()
    for row in rows:
        if row["words"] and taken[row["lang"]] < per_language:
            taken[row["lang"]] += 1
            words += map(bytes, row["words"])
            labels += [languages.index(row["lang"])] * len(row["words"])
    return train(words, np.array(labels, np.int64), languages)


class Labeller:
    """Pooled labels of words, remembered by word."""

    def __init__(self, net: Network):
        self.net, self.place, self.sums, self.used = net, {}, np.zeros((1 << 12, len(net.languages) + 1)), 0

    def _learn(self, words: list[bytes]) -> None:
        if self.used + len(words) > REMEMBERED:
            self.place.clear()
            self.used = 0
        if self.used + len(words) > len(self.sums):
            grown = np.zeros((max(2 * len(self.sums), self.used + len(words)), self.sums.shape[1]))
            grown[: self.used] = self.sums[: self.used]
            self.sums = grown
        pieces = [(s, i) for i, w in enumerate(words) for s in spans(w)]
        pieces.sort(key=lambda p: len(p[0]))
        got = np.zeros((len(words), self.sums.shape[1]))
        for a in range(0, len(pieces), 4096):
            part = pieces[a : a + 4096]
            x, n = matrix([s for s, _ in part])
            p = self.net.probabilities(x, n).sum(axis=0)
            np.add.at(got, np.array([i for _, i in part]), np.column_stack([p, n]))
        self.sums[self.used : self.used + len(words)] = got
        self.place.update(zip(words, range(self.used, self.used + len(words)), strict=True))
        self.used += len(words)

    def documents(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        counts = [Counter(t.encode().split()) if t and _LETTER.search(t) else None for t in texts]
        words = set().union(*filter(None, counts))
        new = [w for w in words if w not in self.place]
        if self.used + len(new) > REMEMBERED:
            self.place.clear()
            self.used = 0
            new = list(words)
        if new:
            self._learn(new)
        names, scores = [], np.zeros(len(texts))
        for i, c in enumerate(counts):
            if not c or not self.net.languages:
                names.append("und")
                continue
            at = np.fromiter(map(self.place.__getitem__, c), np.int64, len(c))
            pooled = np.fromiter(c.values(), float, len(c)) @ self.sums[at]
            p = pooled[:-1] / pooled[-1]
            best = int(p.argmax())
            names.append(self.net.languages[best])
            scores[i] = min(1.0, max(0.0, p[best]))
        return names, scores


def predict(docs: DataFrame, net: Network) -> DataFrame:
    """doc_id, lang_pred, score for every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(net)
    own: list[Labeller] = []

    def fn(batch: pa.RecordBatch):
        if not own:
            own.append(Labeller(shared.value))
        names, scores = own[0].documents(batch.column(1).to_pylist())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(scores)], ["doc_id", "lang_pred", "score"])

    return map_texts(docs, ["doc_id", "text"], fn, "doc_id long, lang_pred string, score double")


def judge(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score: documents with crc32(doc_id) mod 4 = 2 are never learnt from."""
    net = fit(docs, F.coalesce(id_bucket("doc_id", 4) != 2, F.lit(False)))
    return predict(docs, net).select("doc_id", F.coalesce(id_bucket("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")
