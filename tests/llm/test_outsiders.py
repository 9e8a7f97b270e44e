"""Buckets with very many outsiders: one round of comparisons, in which every pair that may be a link meets once."""

from itertools import combinations

from pyspark.sql import Row

from routefront.llm import near_dedup


def test_every_outsider_meets_every_member_once(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "OUTSIDERS", 4)
    monkeypatch.setattr(near_dedup, "BLOCK", 6)
    main = {n: 7 for n in range(1, 14)}
    cls = main | {n: n for n in range(20, 43)}
    rows = [Row(bucket=1, node=n, **{"class": c}, size=len(cls), outsiders=len(cls) - len(main), main=Row(n=len(main), **{"class": 7})["class"]) for n, c in cls.items()]
    state = spark.createDataFrame(rows, "bucket long, node long, class long, size long, outsiders long, main long")
    groups = {}
    for r in near_dedup._dealt(state).collect():
        groups.setdefault((r["part"], r["block"]), []).append((r["node"], r["outside"]))
    met = []
    for (_, block), members in groups.items():
        outside = [n for n, o in members if o]
        met += [tuple(sorted((a, b))) for a in outside for b, o in members if not o]
        if block == 0:
            met += [tuple(sorted(p)) for p in combinations(outside, 2)]
    want = [p for p in combinations(sorted(cls), 2) if not (p[0] in main and p[1] in main)]
    assert sorted(met) == sorted(want)


def test_crowded_buckets_take_no_rounds(spark, monkeypatch):
    """Copies of one text with different edits: as many outsiders as one likes, the same class, and a bounded number of written tables."""
    monkeypatch.setattr(near_dedup, "OUTSIDERS", 2)
    monkeypatch.setattr(near_dedup, "BLOCK", 8)
    labels, write = [], near_dedup.materialise
    monkeypatch.setattr(near_dedup, "materialise", lambda df, label: labels.append(label) or write(df, label))
    base = [f"t{i * 31 % 997}" for i in range(200)]
    texts = []
    for k in range(40):
        w = list(base)
        for j in range(6):  # two of these are often less similar than asked for
            w[(k * 37 + j * 29) % 200] = f"edit{k}x{j}"
        texts.append((k, " ".join(w)))
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.classes(docs).collect()}
    rounds = {x for x in labels if x.startswith("links-")}
    assert rounds <= {"links-0", "links-1"} and not any(x.startswith("leaders") for x in labels)
    assert set(got) == set(range(40))
