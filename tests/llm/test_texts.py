"""Kernels of the text operators against brute force and public libraries."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from routefront.llm import bpe, hmm, language_id, near_dedup, packing, quality_rules, substring_dedup, toxicity, url_filter
from routefront.llm.common import text_views, token_bounds, token_hashes

P = pytest.importorskip("public_tokenizers")
WORDS = "the cat sat on a mat and saw two dogs run far from home while birds sang above".split()


def views(*texts):
    return text_views(pa.array(list(texts), pa.large_string()))


def test_tokens_are_those_of_bytes_split():
    texts = ["", None, "a  b\tc\n", " x", "é ü y", "no"]
    buf, offs = views(*texts)
    start, end, doc = token_bounds(buf, offs)
    got = [(int(d), bytes(buf[a:b])) for a, b, d in zip(start, end, doc)]
    assert got == [(i, w) for i, t in enumerate(texts) for w in (t or "").encode().split()]
    h = token_hashes(buf, start, end)
    assert len(set(h.tolist())) == len({w for _, w in got})


def random_texts(n=400):
    r = random.Random(1)
    parts = ["a", "b", "ab", " ", "  ", "\n", "\t", "é", "ñ", "1", "'s", "漢", "\x1c", "\x85", "　", "aaaa", "...", "\U0001f600", "<|endoftext|>"]
    return ["", "a" * 5000, "ab" * 3000, "aaab" * 999, *("".join(r.choice(parts) for _ in range(r.randint(0, 60))) for _ in range(n))]


def numbers(raw):
    return np.frombuffer(raw, "<u4").tolist()


@pytest.mark.parametrize("few", [0, 12, 1 << 30])
def test_bpe_equals_tiktoken(few, monkeypatch):
    """Buckets as arrays, one by one, and mixed; units remembered or forgotten at once."""
    import tiktoken

    monkeypatch.setattr(bpe, "FEW", few)
    ranks = bpe.load_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    own, dec = bpe.Encoder(bpe.by_queue(ranks, P.PATTERN), most=0 if few else 1 << 20), bpe.Decoder(ranks)
    other = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    texts = random_texts()
    for a in range(0, len(texts), 50):
        for text, raw in zip(texts[a : a + 50], own.encode_all(texts[a : a + 50]), strict=True):
            ids = np.frombuffer(raw, "<u4")
            assert ids.tolist() == other.encode_ordinary(text)
            assert dec.decode(ids).decode() == text and dec.decimals(ids).decode() == ",".join(map(str, ids.tolist()))


def test_packing_ids_equal_the_tokenizers_library():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    enc = packing._packer(P.path("byte_bpe_50k.json"))
    texts = ["Hello there, world!", "two  spaces\n\nand é ü", "one\nline feed here\nand there", "x" * 300, "<|endoftext|> here", "ends in a space ", "ends in a line\n", "a\nb\nc d\ne\nf g", *random_texts(200), *(" ".join(f"u{i}w{k}" + ("\nx" if k % 7 == 0 else "") for k in range(200)) for i in range(3))]
    for text, raw in zip(texts, enc.encode_all(texts), strict=True):
        assert numbers(raw) == t.encode(text, add_special_tokens=False).ids


def histogram(seed, n=2000):
    r = random.Random(seed)
    return dict(Counter(r.choice([1, 3, 17, 100, 500, 700, 1024]) if r.random() < 0.5 else r.randint(1, 1024) for _ in range(n)))


@pytest.mark.parametrize("seed", range(3))
def test_packing_places_every_piece_once(seed):
    h = histogram(seed)
    plan = packing.plan(h)
    plain = sum(times for _, times in packing.best_fit([], dict(h), 1024))
    n = np.concatenate([np.full(c, k) for k, c in h.items()])
    rank = np.concatenate([np.arange(c) for c in h.values()])
    seq, off = plan.place(n, rank)
    order = np.lexsort((off, seq))
    seq, off, n = seq[order], off[order], n[order]
    new = np.append(True, seq[1:] != seq[:-1])
    assert (off == np.where(new, 0, np.append(0, off + n)[:-1])).all() and (off + n).max() <= 1024
    assert plan.sequences == len(set(seq.tolist())) <= plain + 1
    assert packing.plan({}).sequences == 0


@pytest.mark.parametrize("h", [histogram(0), {k: 50 * c for k, c in histogram(1).items()}, {520: 100, 260: 200, 250: 100, 240: 200}, {1024: 3}, {1: 5}])
def test_the_linear_program_covers_every_length_near_its_bound(h):
    lengths = np.array(sorted(h), np.int64)
    c = packing.configuration_lp(lengths, np.array([h[int(n)] for n in lengths]), 1024)
    covered = Counter()
    for key, x in c.runs.items():
        assert x > 0 and sum(n * k for n, k in key) <= 1024
        for n, k in key:
            covered[n] += k * x
    assert all(covered[n] >= h[n] * (1 - 1e-6) for n in h)
    assert c.value == pytest.approx(sum(c.runs.values())) and c.bound >= sum(n * k for n, k in h.items()) / 1024 - 1e-6
    assert c.bound * (1 - 1e-9) <= c.value <= 1.06 * c.bound + 1
    groups, _ = packing.choose(h)
    assert c.bound - 1e-6 <= sum(times for _, times in groups) and {n: sum(g.get(n, 0) * t for g, t in groups) for n in h} == h


def test_the_linear_program_places_most_pieces_of_a_large_histogram():
    h = {k: 200 * c for k, c in histogram(4, 4000).items()}
    lengths = np.array(sorted(h), np.int64)
    c = packing.configuration_lp(lengths, np.array([h[int(n)] for n in lengths]), 1024)
    groups, _ = packing.rounded(c.early[0.9], h, 1024)
    assert sum(k * t for g, t in groups for k in g.values()) > 0.6 * sum(h.values())
    plain = sum(t for _, t in packing.best_fit([], dict(h), 1024))
    assert sum(t for _, t in packing.choose(h)[0]) <= 1.006 * plain  # the cover is within a few thousandths of its bound


def test_cascade_is_exact():
    r = np.random.default_rng(4)
    keys = r.integers(-(1 << 62), 1 << 62, (3000, 2))
    listed, rest = keys[:400], keys[400:]
    levels, sides = [], [listed, rest]
    while len(sides[len(levels) % 2]):
        level = url_filter.Level(len(sides[len(levels) % 2]), 0.2, len(levels) + 1)
        level.add(sides[len(levels) % 2][:, 0].copy(), sides[len(levels) % 2][:, 1].copy())
        levels.append(level)
        other = len(levels) % 2
        sides[other] = sides[other][level.has(sides[other][:, 0].copy(), sides[other][:, 1].copy())]
    assert len(levels) > 2
    got = url_filter.member(levels, keys[:, 0].copy(), keys[:, 1].copy())
    assert got[:400].all() and not got[400:].any()
    with pytest.raises(ValueError):
        url_filter.parse_rules(["deny x.com/"])


def test_gear_is_the_rolling_hash():
    buf = np.frombuffer(random.Random(2).randbytes(500), np.uint8)
    h, want = 0, []
    for b in buf.tolist():
        h = ((h << 1) + int(substring_dedup._GEAR[b])) & 0xFFFF
        want.append(h)
    assert substring_dedup.gear(buf).tolist()[16:] == want[16:]


def test_chunks_cover_texts_and_resist_shifts():
    r = random.Random(5)
    passage = " ".join(r.choice(WORDS) + str(r.randint(0, 99)) for _ in range(60))
    texts = [passage + " one", "", "something else first: é " + passage, "é" * 400]
    buf, offs = views(*texts)
    start, doc = substring_dedup.cuts(buf, offs)
    end = np.append(start[1:], len(buf))
    pieces = [[bytes(buf[a:b]) for a, b, d in zip(start, end, doc) if d == i] for i in range(len(texts))]
    assert [b"".join(p).decode() for p in pieces] == texts
    assert all(x.decode() for p in pieces for x in p)
    shared = set(pieces[0]) & set(pieces[2])
    assert sum(map(len, shared)) > 0.6 * len(passage)


def test_shingles_by_brute_force():
    r = random.Random(6)
    texts = [" ".join(r.choice(WORDS) for _ in range(n)) for n in (0, 1, 4, 5, 6, 40)]
    owner, key, count = near_dedup.shingles(*views(*texts))
    for i, t in enumerate(texts):
        w = t.split()
        want = Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else Counter()
        assert sorted(count[owner == i].tolist()) == sorted(want.values())


def test_samples_estimate_weighted_jaccard():
    r = np.random.default_rng(7)
    keys = r.integers(0, 1 << 63, 400).astype(np.uint64)
    hits = 0
    for trial in range(60):
        a, b = np.sort(r.choice(keys, 100, replace=False)), None
        b = np.sort(np.append(a[:80], r.integers(0, 1 << 63, 20).astype(np.uint64) + np.uint64(trial)))
        w = np.ones(100)
        _, s = near_dedup.sample(np.repeat([0, 1], 100), np.concatenate([a, b]), np.concatenate([w, w]))
        hits += int((s[0] == s[1]).sum())
    assert abs(hits / (60 * near_dedup.SAMPLES) - 80 / 120) < 0.05
    assert near_dedup.similarity(a, w, b, w) == pytest.approx(80 / 120)


def test_counts_of_quality_by_brute_force():
    r = random.Random(8)
    for _ in range(100):
        text = "".join(r.choice(["ab", "c", "é", " ", " ", "\n", "#", "|", "!", " ", "AB "]) for _ in range(r.randint(0, 80)))
        w = text.encode().split()
        grams = Counter(zip(w, w[1:], w[2:]))
        mark = {j for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
        seen, dup = set(), 0
        for line in text.split("\n"):
            if line.encode().split():
                dup += line in seen
                seen.add(line)
        got = dict(zip(quality_rules.COUNTS, quality_rules.count_text(text)))
        assert (got["n_words"], got["n_repeat_words"], got["n_dup_lines"]) == (len(w), len(mark), dup)
        assert got["word_chars"] == sum(len(x.decode()) for x in w) and got["n_symbols"] == sum(c in "#*$%&|<>" for c in text)


def test_decision_list_learns_a_threshold():
    r = np.random.default_rng(9)
    x = {n: r.random(400) for n, _, _ in quality_rules.RATIOS}
    bad = (x["upper_share"] > 0.7) | (x["symbols_per_word"] > 0.8)
    fired = np.zeros(400, bool)
    for rule in quality_rules.learn(x, bad):
        fired |= quality_rules._holds(rule, x)
    assert (fired == bad).mean() > 0.95
    assert quality_rules.learn(x, np.zeros(400, bool)) == []


def test_forward_recursion_by_enumeration():
    import itertools

    r = np.random.default_rng(10)
    s = hmm.STATES
    hmm_model = hmm.Model(r.dirichlet(np.ones(s)), r.dirichlet(np.ones(s), s), r.dirichlet(np.ones(5), s).T)
    seq = np.array([0, 3, 1], np.int32)
    total = sum(hmm_model.start[p[0]] * hmm_model.emit[0, p[0]] * hmm_model.move[p[0], p[1]] * hmm_model.emit[3, p[1]] * hmm_model.move[p[1], p[2]] * hmm_model.emit[1, p[2]] for p in itertools.product(range(s), repeat=3))
    two = [np.array([2], np.uint16), seq.astype(np.uint16)]
    assert hmm.Sequences(two).likelihoods(hmm_model)[1] == pytest.approx(np.log(total))
    assert hmm.runs(two) == [[1, 0]]
    before, starts, moves, emits = hmm.Sequences([seq] * 4).expected(hmm_model)
    assert moves.sum() == pytest.approx(8) and emits.sum() == pytest.approx(12) and starts.sum() == pytest.approx(4)
    assert before == pytest.approx(4 * np.log(total))
    at = lambda p: hmm_model.start[p[0]] * hmm_model.emit[0, p[0]] * hmm_model.move[p[0], p[1]] * hmm_model.emit[3, p[1]] * hmm_model.move[p[1], p[2]] * hmm_model.emit[1, p[2]]
    want = sum(at(p) for p in itertools.product(range(s), repeat=3) if p[0] == 2 and p[1] == 1) + sum(at(p) for p in itertools.product(range(s), repeat=3) if p[1] == 2 and p[2] == 1)
    assert moves[2, 1] == pytest.approx(4 * want / total)


def test_multiple_instance_learning_finds_the_sentence():
    r = random.Random(11)
    texts = [". ".join(" ".join(r.choice(WORDS) for _ in range(6)) for _ in range(5)) for _ in range(200)]
    labels = np.array([i % 4 == 0 for i in range(200)], np.int64)
    texts = [t + ". you nasty grumbler" if y else t for t, y in zip(texts, labels)]
    words, first, doc, at = toxicity.features(*views(*texts))
    m = toxicity.train(toxicity.split_documents(words, first, doc, 200), labels)
    p, z, doc, at = toxicity._scores(pa.array(texts, pa.large_string()), 200, m)
    assert ((p >= 0.7) == (labels == 1)).mean() > 0.97
    worst = at[doc == 0][np.argmax(z[doc == 0])]
    assert texts[0].encode()[worst:].startswith(b"you nasty")
    assert toxicity._scores(pa.array(["", None], pa.large_string()), 2, m)[0].tolist() == [0.0, 0.0]


def test_gradients_of_the_language_network_by_differences():
    """Backpropagation through time against central differences, in double precision."""
    r = np.random.default_rng(13)
    net = language_id.Network.start(["a", "b", "c"], hidden=4, seed=2)
    net.table, net.recur, net.bias = ([p.astype(float) for p in side] for side in (net.table, net.recur, net.bias))
    net.out, net.out_bias = net.out.astype(float), net.out_bias.astype(float)
    x, n = language_id.matrix([b"abca", b"b", b"cabbage", b"ab"])
    y = np.array([0, 1, 2, 1])
    _, grads = net.gradients(x, n, y)
    for p, g in zip(net.parameters(), grads, strict=True):
        used = np.argwhere(np.abs(g) > 1e-3)
        for at in map(tuple, used[r.permutation(len(used))[:6]]):
            eps, old = 2e-2, p[at]
            p[at] = old + eps
            up = net.gradients(x, n, y)[0]
            p[at] = old - eps
            down = net.gradients(x, n, y)[0]
            p[at] = old
            assert (up - down) / (2 * eps) == pytest.approx(g[at], rel=0.05, abs=2e-4)
