"""Operators on Spark: odd rows, and small tables against brute force."""

import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from routefront.llm import bpe, exact_dedup, hmm, language_id, near_dedup, packing, quality_rules, substring_dedup, toxicity, url_filter

P = pytest.importorskip("public_tokenizers")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, run int, node string"
LONG = " ".join(f"w{i * 7919 % 1000}" for i in range(70))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, ties, repeated rows, and extra columns with names that operators use inside."""
    texts = [None, "", "  \n", "Same text here", "Same  text\there", "Same text here", LONG, LONG + " tail", "start. " + LONG, "x" * 30_000, "word " * 5000, "Ein kurzer Text über nichts."]
    rows = [(i, t, ["en", "de", None][i % 3], None if i % 4 == 0 else "s", None if t is None else len(t), i, "n") for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[3], (None, "no id", None, None, 5, 1, "n")], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, int(i % 5 == 0)) for i in range(12)] + [(None, 1, 1), (99, None, None)], "doc_id long, quality int, toxic int")


def operators(labels):
    ranks, more = P.path("byte_bpe_50k.json"), P.path("byte_bpe_multi_50k.tiktoken")
    return {
        "pack": lambda d: packing.pack(d, ranks),
        "exact": exact_dedup.groups,
        "exact_filter": exact_dedup.deduplicate,
        "language": language_id.judge,
        "bpe": lambda d: bpe.round_trip(d, more, P.PATTERN),
        "substring": substring_dedup.remove_repeats,
        "lm": hmm.score,
        "toxicity": lambda d: toxicity.judge(d, labels),
        "toxicity_filter": lambda d: toxicity.keep_clean(d, labels),
        "near": near_dedup.classes,
        "near_filter": near_dedup.deduplicate,
        "quality": lambda d: quality_rules.judge(d, labels),
    }


ONE_TO_ONE = {"exact", "language", "bpe", "substring", "lm", "toxicity", "near", "quality"}


@pytest.mark.parametrize("name", list(operators(None)))
def test_odd_and_empty_tables(name, odd, labels):
    f = operators(labels)[name]
    got = f(odd).collect()
    if name in ONE_TO_ONE:
        assert len(got) == odd.count()
    assert f(odd.limit(0)).collect() == []


def test_exact_groups_by_brute_force(odd):
    got = {(r["doc_id"], r["kept"]): r for r in exact_dedup.groups(odd, support=0.2).collect()}
    rows = exact_dedup.groups(odd).collect()
    assert sorted(map(str, rows)) == sorted(map(str, exact_dedup.groups(odd, support=0.2).collect()))  # heavy or not
    assert got[3, True]["group_size"] == 4 and got[4, False]["keep_id"] == 3 and got[5, False]["keep_id"] == 3
    assert got[0, True]["group_size"] == 2 and got[1, False]["keep_id"] == 0
    kept = [r["doc_id"] for r in exact_dedup.deduplicate(odd).collect()]
    assert sorted(kept, key=str) == sorted((r["doc_id"] for r in rows if r["kept"]), key=str)


def test_near_copies_and_passages(odd):
    c = {r["doc_id"]: r for r in near_dedup.classes(odd).where("doc_id is not null").collect()}
    assert c[7]["class_id"] == c[8]["class_id"] == 6 and c[3]["class_id"] == c[4]["class_id"] == 3 and c[9]["class_size"] == 1
    out = {r["doc_id"]: r for r in substring_dedup.remove_repeats(odd).where("doc_id is not null").collect()}
    assert out[6]["text"] == LONG and len(out[8]["text"]) < 200 and out[8]["n_chars"] == len(out[8]["text"])
    assert out[3]["text"] == "Same text here" and out[10]["text"] == "word " * 5000


def test_many_near_copies_form_one_class(spark):
    """A bucket whose members are far from its leader: classes meet through other members."""
    base = [f"t{i * 31 % 997}" for i in range(200)]
    rows = []
    for k in range(60):
        w = list(base)
        w[(k * 3) % 200] = f"edit{k}"
        rows.append((k, " ".join(w)))
    rows += [(100 + k, " ".join(f"u{k}x{i}" for i in range(100))) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    c = {r["doc_id"]: r["class_id"] for r in near_dedup.classes(docs).collect()}
    assert {c[k] for k in range(60)} == {0} and all(c[100 + k] == 100 + k for k in range(40))


def test_packing_rows_are_whole(odd):
    rows = packing.pack(odd, P.path("byte_bpe_50k.json")).collect()
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by.values():
        at = 0
        for offset, n in sorted(places):
            assert offset == at
            at += n
        assert at <= 1024
    nine = sorted((r["piece"], r["start"], r["length"]) for r in rows if r["doc_id"] == 9)
    assert all(b[1] == a[1] + a[2] and b[2] == 1024 for a, b in zip(nine, nine[1:]))
    empty = next(r for r in rows if r["doc_id"] == 1)
    assert empty["length"] == 1 and empty["ids_crc32"] == zlib.crc32(np.array([2], "<u4").tobytes())


def test_bpe_columns_equal_tiktoken(odd):
    import hashlib

    import tiktoken

    path = P.path("byte_bpe_multi_50k.tiktoken")
    t = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.load_ranks(path), special_tokens={})
    sha = lambda x: hashlib.sha256(x).hexdigest()
    want = []
    for r in odd.select("doc_id", "text").collect():
        ids = t.encode_ordinary(r["text"] or "")
        want.append((r["doc_id"], len(ids), sha(",".join(map(str, ids)).encode()), sha((r["text"] or "").encode())))
    assert sorted(map(str, want)) == sorted(str(tuple(r)) for r in bpe.round_trip(odd, path, P.PATTERN).collect())


@pytest.mark.parametrize("support", [0.0, 0.0005, 1.0])
def test_repeated_passages_by_brute_force(spark, support):
    """Every chunk of a later document that an earlier one has, joined to runs; with frequent digests by broadcast and without."""
    shared = [" ".join(f"p{k}w{i * 7919 % 997}" for i in range(60)) for k in range(3)]
    texts = [" ".join([f"d{i}x{j * 31 % 89}" for j in range(20)] + [shared[i % 3]] * (1 + (i % 5 == 0)) + [f"e{i}y{j}" for j in range(15)]) for i in range(30)]
    docs = spark.createDataFrame([(29 - i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    order = [(29 - i, t.encode()) for i, t in enumerate(texts)][::-1]
    for within in (False, True):
        want, first = [], {}
        parts = {}
        for doc, raw in order:
            start, _ = substring_dedup.cuts(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
            parts[doc] = [(int(a), raw[a:b]) for a, b in zip(start, [*start[1:], len(raw)])]
            for _, c in parts[doc]:
                first.setdefault(c, doc)
        for doc, _ in order:
            seen, run = set(), None
            for a, c in [*parts[doc], (None, None)]:
                if c is not None and (first[c] != doc or (within and c in seen)):
                    run = (run[0], run[1] + c) if run else (a, c)
                else:
                    if run:
                        want.append((doc, run[0], len(run[1])))
                    run = None
                seen.add(c)
        got = substring_dedup.repeated_passages(docs, 0, within, support).collect()
        assert sorted(want) == sorted((r["doc_id"], r["start"], r["length"]) for r in got)
        assert sum(r["words"] >= 50 for r in got) >= 27  # the passage of every later document


def test_near_classes_by_all_pairs(spark):
    """Exact weighted similarity of all pairs, joined to classes: recall of its links and no false class."""
    r = np.random.default_rng(12)
    texts = []
    for k in range(25):
        base = [f"b{k}w{i * 17 % 311}" for i in range(int(r.integers(120, 300)))]
        for _ in range(int(r.integers(1, 7))):
            w = list(base)
            for _ in range(int(r.integers(0, 4))):
                w[int(r.integers(len(w)))] = f"n{int(r.integers(1 << 30))}"
            texts.append(" ".join(w))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    weights = near_dedup.document_weights(docs)
    vectors = []
    for t in texts:
        _, key, count = near_dedup.shingles(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t.encode())]))
        vectors.append((key, weights.of(key, count)))
    parent = list(range(len(texts)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    links = [(i, j) for i in range(len(texts)) for j in range(i) if near_dedup.similarity(*vectors[i], *vectors[j]) >= near_dedup.SIMILAR]
    for i, j in links:
        parent[max(find(i), find(j))] = min(find(i), find(j))
    got = {x["doc_id"]: x["class_id"] for x in near_dedup.classes(docs).collect()}
    assert len(links) > 30 and sum(got[i] == got[j] for i, j in links) >= 0.97 * len(links)
    assert all(find(i) == find(got[i]) for i in got)  # nothing joined that no chain of links joins


def test_urls_by_brute_force(spark):
    rules = url_filter.parse_rules(["block com/en/", "allow example.com/en/7", "allow net/de/", "block example.net/de/8", "block org/es/"])
    urls = [None, "", "no scheme", "http://A.Example.COM/en/7x?q#f", "https://example.com/en/8", "https://com/en/", "http://xcom/en/1", "https://b.example.net/de/80", "http://b.example.net/de/9#t", "http://q.org/es", "http://q.org/es/", "ftp://", "http://h?x=/en/", "http://h.com#/en/"]
    got = url_filter.judge(spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, host string"), rules).collect()
    for r in got:
        u = urls[r["page_id"]] or ""
        rest = u.partition("://")[2] if "://" in u else ""
        cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        host, path = rest[:cut].lower(), rest[cut:].split("?")[0].split("#")[0]
        fits = [x for x in rules if (host == x.host or host.endswith("." + x.host)) and path.startswith(x.path)]
        best = max(fits, key=lambda x: len(x.key), default=None)
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == (host, path, best and best.key, best.verdict if best else "allow")


def test_base_scores_by_brute_force(odd):
    rows = odd.select("doc_id", "text").collect()
    tokens = [(r["doc_id"], (r["text"] or "").encode().lower().split() + [b""]) for r in rows]
    learn = Counter(w for i, t in tokens if i is not None and zlib.crc32(str(i).encode()) % 5 != 1 for w in t)
    n, v = sum(learn.values()), len(learn)
    want = sorted(round(sum(np.log10((learn[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t), 6) for _, t in tokens)
    got = hmm.score(odd).collect()
    assert sorted(round(r["base_score"], 6) for r in got) == want and all(r["score"] < 0 for r in got) and got[0]["train_tokens"] == n


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    got = language_id.judge(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.where(F.col("lang") == F.col("lang_pred")).count() > 0.97 * got.count()


def test_toxicity_learns_from_the_stated_number_of_labels(spark):
    """A rare toxic word whose evidence is spread over 9000 labels, and one that only stands in texts of over 200,000 bytes."""
    rare = {i for i in range(9000) if i % 750 == 1}
    text = lambda i: f"plain words number w{i % 50} here" + (" zlorbish" if i in rare else "")
    long = [(9000 + i, "quiet filler words " * 11_000 + ("Grumfable now." if i % 2 else "")) for i in range(24)]
    docs = spark.createDataFrame([*((i, text(i)) for i in range(9000)), *long], "doc_id long, text string")
    labels = spark.createDataFrame([*((i, int(i in rare)) for i in range(9000)), *((9000 + i, i % 2) for i in range(24))], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    asked = spark.createDataFrame([(1, "words with zlorbish here"), (2, "Grumfable now."), (3, "plain words here")], "doc_id long, text string")
    got = {r["doc_id"]: r["score"] for r in toxicity.score(asked, model).collect()}
    assert got[1] > 0.7 and got[2] > 0.7 and got[3] < 0.1


def test_toxicity_model_is_the_one_of_all_words(spark):
    docs = spark.createDataFrame([(i, f"some text t{i % 7}. " + ("vile thing" if i % 3 == 0 else "nice thing")) for i in range(60)] + [(60, "")], "doc_id long, text string")
    labels = docs.select("doc_id", (F.col("doc_id") % 3 == 0).cast("int").alias("toxic"))
    model = toxicity.fit(docs, labels)
    texts = [r["text"] for r in docs.orderBy("doc_id").collect()]
    raw = [t.encode() for t in texts]
    words, first, doc, _ = toxicity.features(np.frombuffer(b"".join(raw), np.uint8), np.append(0, np.cumsum([len(t) for t in raw])))
    want = toxicity.train(toxicity.split_documents(words, first, doc, len(texts)), np.array([int(i % 3 == 0) for i in range(61)]))
    assert np.array_equal(model.weights, want.weights) and model.bias == want.bias and np.any(want.weights)


@pytest.mark.parametrize("parts", [1, 30])
def test_document_frequencies_count_every_document(spark, parts):
    """Frequencies by brute force, with two documents a task as with all in one."""
    same, often, rare = ("all of them say this", "every second one says that", "every fourth one says so")
    texts = [" ".join([f"w{i}x{j}" for j in range(6)] + [same] + ([often] if i % 2 else []) + ([rare] if i % 4 == 0 else [])) for i in range(60)]
    docs = spark.createDataFrame(spark.sparkContext.parallelize([(i, t) for i, t in enumerate(texts)], parts), "doc_id long, text string")
    found = Counter()
    for t in texts:
        found.update(set(near_dedup.shingles(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t)]))[1].tolist()))
    want = {k: (np.log1p(60 / n) / np.log1p(1 / near_dedup.FLOOR)) ** near_dedup.DAMP for k, n in found.items() if n > 1}
    got = near_dedup.document_weights(docs)
    assert want and dict(zip(got.keys.tolist(), got.values.tolist())) == pytest.approx(want)


def test_pipeline_stages_on_odd_and_empty_tables(spark, odd, labels, tmp_path):
    """Every stage on what its predecessor kept: nulls, empty and long texts, copies, repeated rows, clashing names; and on no rows."""
    pipeline = pytest.importorskip("corpus_pipeline")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    docs, kept = odd, {}
    for k, (name, stage) in enumerate(pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        if name != pipeline.STAGES[-1][0]:
            assert out.schema.names == odd.schema.names
        out.write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        kept[name] = sorted((r["doc_id"] for r in docs.collect()), key=str)
        assert stage(spark, odd.limit(0), str(tmp_path)).collect() == []
    copies = kept["exact_dedup"]
    assert len(kept["toxicity"]) >= 12 and copies.count(3) == 1 and 4 not in copies and 5 not in copies and 1 not in copies
    assert {6, 9, 10} <= set(kept["near_dedup"]) and not {7, 8} & set(kept["near_dedup"])
    assert kept["substring_dedup"] == kept["near_dedup"] and set(kept["best_fit_packing"]) == set(kept["near_dedup"])
