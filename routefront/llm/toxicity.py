"""Toxicity by multiple-instance learning: sentences are the instances, the document's label the only supervision.

A sentence's score is a logistic function of hashed words; noisy-or makes the document's, P = 1 - prod(1 - p). With
softplus(z) = -log(1 - p) the document is 1 - exp(-sum softplus(z)), whose gradient reaches the sentences that explain
a positive label. The trained weights locate offending sentences. Training reads whole texts of at most `sample_docs`
labelled documents (by hash of the id); their features are written once, the words' document counts are summed over the
executors, and only words that are learnt reach the driver. Scoring reads every whole text, a slice at a time.

Cases: a null, empty or wordless text has no sentence and scores 0; with no positive label in the sample every score is
near 0; labels without a document, null labels and repeated rows are ignored or repeated as they come; an empty table
gives an empty result; only doc_id, text and labels' doc_id, toxic are read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_bucket, lower_ascii, map_texts, materialise, text_column, text_views, token_bounds, token_hashes

#: Hash buckets of words, labelled documents that training may read, passes over them.
BUCKETS, SAMPLE_DOCS, EPOCHS = 1 << 17, 12000, 80
#: Bytes of a word's beginnings that are features beside the word, for stems with endings.
PREFIXES = (4, 5, 6)
#: Documents of the sample a word must occur in, standard errors taken off its log odds, pull back to those odds, weight of a toxic document.
LEAST_DOCS, DOUBT, ANCHOR, FAVOUR = 3, 2.0, 0.1, 3.0
#: A score from which a document counts as toxic.
THRESHOLD = 0.7

_BREAK = np.zeros(256, bool)
_BREAK[[ord(c) for c in ".!?\n"]] = True
_OUTSIDE = np.ones(256, bool)
_OUTSIDE[[*range(ord("0"), ord("9") + 1), *range(ord("a"), ord("z") + 1), ord("'"), *range(0x80, 0x100)]] = False


@dataclass
class Model:
    weights: np.ndarray
    bias: float

    def sentences(self, words: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Logit of each sentence; starts: index of its first word."""
        return np.add.reduceat(self.weights[words], starts) + self.bias if len(starts) else np.zeros(0)


def features(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of words and their beginnings, first bucket of each sentence, document of each sentence, byte where each sentence's words begin."""
    buf = lower_ascii(buf)
    starts, ends, doc = token_bounds(buf, offs, _OUTSIDE)
    if not len(starts):
        z = np.zeros(0, np.int64)
        return z, z, z, z
    parts = [token_hashes(buf, starts, ends), *(token_hashes(buf, starts, np.minimum(starts + n, ends)) + np.uint64(n) for n in PREFIXES)]
    words = (np.stack(parts, axis=1).ravel() % np.uint64(BUCKETS)).astype(np.int64)
    breaks = np.cumsum(_BREAK[buf])[starts]
    new = np.ones(len(starts), bool)
    new[1:] = (breaks[1:] != breaks[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    sentence = np.repeat(np.cumsum(new) - 1, len(parts))
    once = np.unique(sentence * BUCKETS + words)  # a word counts once in a sentence
    return once % BUCKETS, np.searchsorted(once, np.arange(len(first)) * BUCKETS), doc[first], starts[first]


def softplus(z: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, z)


Instances = tuple[np.ndarray, np.ndarray]  # a document's word buckets, sentence after sentence, and how many each sentence has


def split_documents(words: np.ndarray, first: np.ndarray, doc: np.ndarray, n: int) -> list[Instances]:
    """`features` of n texts, document by document."""
    sizes = np.diff(np.append(first, len(words)))
    at = np.searchsorted(doc, np.arange(n + 1))
    cut = np.append(first, len(words))[at]
    return [(words[cut[i] : cut[i + 1]].astype(np.int32), sizes[at[i] : at[i + 1]].astype(np.int32)) for i in range(n)]


def cautious_odds(clean: np.ndarray, toxic: np.ndarray, labels: np.ndarray, least: int = LEAST_DOCS, doubt: float = DOUBT) -> tuple[np.ndarray, np.ndarray]:
    """Buckets that are learnt and the weights they start from. clean, toxic: documents that have a bucket.

    A word's weight starts as its log odds between toxic and clean documents, drawn to zero by `doubt` standard errors;
    words without such evidence, or in fewer than `least` documents, are not learnt.
    """
    n = labels.sum()
    odds = np.log((toxic + 0.5) / (n + 1)) - np.log((clean + 0.5) / (len(labels) - n + 1))
    w0 = np.sign(odds) * np.maximum(np.abs(odds) - doubt * np.sqrt(1 / (toxic + 0.5) + 1 / (clean + 0.5)), 0)
    used = np.flatnonzero((w0 != 0) & (toxic + clean >= least))
    return used, w0[used]


def learnt_words(documents: list[Instances], place: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, int]]:
    """Of each document: places of its learnt words, the sentence of each, and the number of sentences. place: -1 for a bucket that is not learnt."""
    out = []
    for words, sizes in documents:
        p = place[words]
        sentence = np.repeat(np.arange(len(sizes), dtype=np.int32), sizes)
        out.append((p[p >= 0], sentence[p >= 0], len(sizes)))  # words that are not learnt weigh nothing
    return out


def descend(documents: list[tuple[np.ndarray, np.ndarray, int]], labels: np.ndarray, used: np.ndarray, start: np.ndarray, epochs: int = EPOCHS, rate: float = 0.05) -> Model:
    """Adam on the noisy-or likelihood, from cautious log odds. documents: `learnt_words`; labels: 0/1 of each document."""
    w, bias = np.zeros(BUCKETS), -6.0
    if not documents or not labels.any():
        return Model(w, -12.0)
    count = np.array([n for _, _, n in documents])
    total_sentences = int(count.sum())
    begin = np.cumsum(count) - count
    words = np.concatenate([p for p, _, _ in documents])
    sentence = np.concatenate([s + b for (_, s, _), b in zip(documents, begin.tolist(), strict=True)])
    doc = np.repeat(np.arange(len(documents), dtype=np.int32), count)
    wu = start.copy()
    m, v = np.zeros(len(wu) + 1), np.zeros(len(wu) + 1)
    positive = labels == 1
    for t in range(1, epochs + 1):
        z = np.bincount(sentence, wu[words], total_sentences) + bias
        total = np.bincount(doc, softplus(z), len(labels))
        # dL/dS: 1 for a clean document, -1/(exp(S) - 1) for a toxic one
        slope = np.where(positive, -FAVOUR / np.maximum(np.expm1(np.minimum(total, 50)), 1e-3), 1.0)
        dz = slope[doc] / (1 + np.exp(-np.clip(z, -50, 50)))
        g = np.append(np.bincount(words, dz[sentence], len(wu)) + ANCHOR * (wu - start), dz.sum())
        m = 0.9 * m + 0.1 * g
        v = 0.99 * v + 0.01 * g * g
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-2)
        wu -= step[:-1]
        bias -= step[-1]
    w[used] = wu
    return Model(w, float(bias))


def train(documents: list[Instances], labels: np.ndarray) -> Model:
    """Model from all words of the documents, at one place."""
    seen = np.zeros((2, BUCKETS))  # documents that have a word: clean, toxic
    for (words, _), y in zip(documents, labels.tolist(), strict=True):
        seen[int(y), np.unique(words)] += 1
    used, start = cautious_odds(*seen, labels)
    return descend(learnt_words(documents, _places(used)), labels, used, start)


def _places(used: np.ndarray) -> np.ndarray:
    place = np.full(BUCKETS, -1, np.int32)
    place[used] = np.arange(len(used), dtype=np.int32)
    return place


def _instances(batch: pa.RecordBatch) -> list[Instances]:
    return [(np.frombuffer(w.as_buffer(), np.int32), np.frombuffer(s.as_buffer(), np.int32)) for w, s in zip(batch.column("words"), batch.column("sizes"), strict=True)]


def fit(docs: DataFrame, labels: DataFrame, learn: Column | None = None, sample_docs: int = SAMPLE_DOCS) -> Model:
    """Model from a bounded sample of the labelled rows for which `learn` holds (a condition on labels' doc_id)."""
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull())
    if learn is not None:
        known = known.where(learn)
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    texts = docs.select("doc_id", "text").where(F.col("text").isNotNull()).join(F.broadcast(chosen), "doc_id")

    def fn(batch: pa.RecordBatch):
        buf, offs = text_views(batch.column(1))
        words, first, doc, _ = features(buf, offs)
        parts = split_documents(words, first, doc, batch.num_rows)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(2), pa.array([p[0].tobytes() for p in parts], pa.binary()), pa.array([p[1].tobytes() for p in parts], pa.binary())],
            ["doc_id", "toxic", "words", "sizes"],
        )

    rows = materialise(map_texts(texts, ["doc_id", "text", "toxic"], fn, "doc_id long, toxic int, words binary, sizes binary"), "toxicity-features")

    if rows.count() > sample_docs:  # ids that repeat
        rows = materialise(rows.orderBy(F.xxhash64("doc_id"), "doc_id", "words").limit(sample_docs), "toxicity-sample")

    def count(batches):
        seen = np.zeros((2, BUCKETS), np.int64)  # documents that have a word: clean, toxic
        for batch in batches:
            for (words, _), y in zip(_instances(batch), batch.column("toxic").to_pylist(), strict=True):
                seen[int(y), np.unique(words)] += 1
        hit = np.flatnonzero(seen.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(hit), pa.array(seen[0, hit]), pa.array(seen[1, hit])], ["bucket", "clean", "toxic"])

    sums = rows.mapInArrow(count, "bucket long, clean long, toxic long").groupBy("bucket").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic")).toArrow()  # at most BUCKETS rows
    seen = np.zeros((2, BUCKETS))
    for i, side in enumerate(("clean", "toxic")):
        seen[i, sums.column("bucket").to_numpy()] = sums.column(side).to_numpy()
    y = np.array([r["toxic"] for r in rows.select("toxic").collect()], np.int64)
    if not y.any():
        return train([], y)
    used, start = cautious_odds(*seen, y)
    shared = docs.sparkSession.sparkContext.broadcast(_places(used))

    def learnt(batches):
        for batch in batches:
            parts = learnt_words(_instances(batch), shared.value)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("toxic"), pa.array([p[0].tobytes() for p in parts], pa.binary()), pa.array([p[1].tobytes() for p in parts], pa.binary()), pa.array([p[2] for p in parts], pa.int64())],
                ["doc_id", "toxic", "words", "sentence", "sentences"],
            )

    found = rows.mapInArrow(learnt, "doc_id long, toxic int, words binary, sentence binary, sentences long").collect()  # at most sample_docs labels
    found.sort(key=lambda r: r["doc_id"])
    documents = [(np.frombuffer(r["words"], np.int32), np.frombuffer(r["sentence"], np.int32), r["sentences"]) for r in found]
    return descend(documents, np.array([r["toxic"] for r in found], np.int64), used, start)


def _scores(batch_text: pa.Array, n: int, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    buf, offs = text_views(batch_text)
    words, first, doc, at = features(buf, offs)
    z = model.sentences(words, first)
    return 1 - np.exp(-np.bincount(doc, softplus(z), n)), z, doc, at - offs[doc]


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, worst_start (byte where the likeliest sentence begins, null if there is none)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def fn(batch: pa.RecordBatch):
        p, z, doc, at = _scores(batch.column(1), batch.num_rows, shared.value)
        worst = np.full(batch.num_rows, -1)
        order = np.argsort(z, kind="stable")
        worst[doc[order]] = at[order]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p), pa.array(worst, mask=worst < 0)], ["doc_id", "score", "worst_start"])

    return map_texts(docs, ["doc_id", "text"], fn, "doc_id long, score double, worst_start long", 1 << 19)


def offending_sentences(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """doc_id, start (byte), p: sentences whose own probability reaches the threshold."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def fn(batch: pa.RecordBatch):
        _, z, doc, at = _scores(batch.column(1), batch.num_rows, shared.value)
        p = 1 / (1 + np.exp(-z))
        hit = np.flatnonzero(p >= threshold)
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(doc[hit])), pa.array(at[hit]), pa.array(p[hit])], ["doc_id", "start", "p"])

    return map_texts(docs, ["doc_id", "text"], fn, "doc_id long, start long, p double")


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted: labels with crc32(doc_id) mod 3 = 1 are never learnt from."""
    model = fit(docs, labels, id_bucket("doc_id", 3) != 1)
    return score(docs, model).select(
        "doc_id", F.coalesce(id_bucket("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "worst_start"
    )


def keep_clean(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs whose score stays below the threshold, all columns; only the texts pass through Python."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, id_bucket("doc_id", 3) != 1))
    p = text_column(lambda texts: pa.array(_scores(texts, len(texts), shared.value)[0]), "double")
    return docs.where(p("text") < THRESHOLD)
