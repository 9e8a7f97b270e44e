"""Quality rules as a learned decision list: sequential covering over labelled statistics.

Rules for low quality are grown one at a time: a conjunction of thresholds that gains most by FOIL's measure on the
growing part of the labelled rows, then cut back to the prefix of conditions that is worth most on the pruning part.
A rule is kept while it is mostly right there. The list becomes one ordered Spark expression (WHEN ... THEN ... ELSE),
so judging a document is a projection over its statistics. Learning reads statistics of a bounded sample of labelled
rows (`sample_rows`, by hash of the id); statistics are taken of every whole text.

Cases: a null, empty or wordless text has zero statistics and fails the base rule; labels that are null or without a
document are ignored; with labels of one kind only the list is empty and the base rule decides; repeated rows are
judged each; an empty table gives an empty result; only doc_id, text and labels' doc_id, quality are read.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_texts, materialise

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"
#: Labelled rows that learning may read, thresholds tried per statistic, rules and conditions at most.
SAMPLE_ROWS, CUTS, MOST_RULES, MOST_CONDITIONS = 20_000, 48, 12, 4
#: Share of right rows, of the pruning part, below which a rule ends the list.
LEAST_RIGHT = 0.7

COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_marks", "n_lines", "n_distinct_words"]
#: Ratios that rules may test: name, numerator, denominator (at least 1).
RATIOS = [
    ("symbols_per_word", "n_symbols", "n_words"),
    ("repeated_share", "n_repeat_words", "n_words"),
    ("dup_line_share", "n_dup_lines", "n_lines"),
    ("upper_share", "n_upper", "word_chars"),
    ("marks_per_word", "n_marks", "n_words"),
    ("chars_per_word", "word_chars", "n_words"),
    ("distinct_share", "n_distinct_words", "n_words"),
    ("words_per_line", "n_words", "n_lines"),
]
_UPPER = bytes(range(ord("A"), ord("Z") + 1))


def count_text(text: str) -> tuple[int, ...]:
    """The counts of one whole text, in the order of COUNTS."""
    raw = text.encode("utf-8")
    words = raw.split()
    n = len(words)
    grams = Counter(zip(words, words[1:], words[2:], strict=False))
    repeated = 0
    if n > 2 and len(grams) < n - 2:
        until = 0  # words before this place are counted
        for i, g in enumerate(zip(words, words[1:], words[2:], strict=False)):
            if grams[g] > 1:
                repeated += i + 3 - max(i, until)
                until = i + 3
    seen, dup, lines = set(), 0, 0
    for line in text.split("\n"):
        if line.strip(BLANKS):
            lines += 1
            dup += line in seen
            seen.add(line)
    return (
        n,
        len(text) - sum(map(text.count, BLANKS)),
        sum(map(text.count, SYMBOLS)),
        dup,
        repeated,
        len(raw) - len(raw.translate(None, _UPPER)),
        text.count("!") + text.count("?"),
        lines,
        len(set(words)),
    )


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id and the counts of every whole text."""

    def fn(batch: pa.RecordBatch):
        rows = [count_text(t or "") for t in batch.column(1).to_pylist()]
        cols = np.array(rows, np.int64).reshape(len(rows), len(COUNTS))
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(cols[:, i]) for i in range(len(COUNTS)))], ["doc_id", *COUNTS])

    return map_texts(docs, ["doc_id", "text"], fn, "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS))


def ratio(top: str, bottom: str) -> Column:
    return F.col(top).cast("double") / F.greatest(F.col(bottom), F.lit(1)).cast("double")


@dataclass(frozen=True)
class Condition:
    name: str
    above: bool
    cut: float

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.name] > self.cut if self.above else x[self.name] <= self.cut

    def column(self) -> Column:
        top, bottom = next((t, b) for n, t, b in RATIOS if n == self.name)
        return ratio(top, bottom) > self.cut if self.above else ratio(top, bottom) <= self.cut


Rule = tuple[Condition, ...]


def _holds(rule: Rule, x: dict[str, np.ndarray]) -> np.ndarray:
    out = np.ones(len(next(iter(x.values()))), bool)
    for c in rule:
        out &= c.holds(x)
    return out


def _grow(x: dict[str, np.ndarray], bad: np.ndarray) -> Rule:
    """Adds the condition of greatest FOIL gain until no good row is covered."""
    rule: Rule = ()
    inside = np.ones(len(bad), bool)
    while len(rule) < MOST_CONDITIONS and (inside & ~bad).any():
        p0, n0 = (inside & bad).sum(), (inside & ~bad).sum()
        best, gain = None, 1e-9
        for name, v in x.items():
            values = np.unique(v[inside])
            mids = (values[1:] + values[:-1]) / 2
            if len(mids) > CUTS:
                mids = np.unique(np.quantile(mids, np.linspace(0, 1, CUTS)))
            for cut in mids.tolist():
                up = inside & (v > cut)
                for above, got in ((True, up), (False, inside & ~up)):
                    p, n = (got & bad).sum(), (got & ~bad).sum()
                    if p:
                        g = p * (np.log2(p / (p + n)) - np.log2(p0 / (p0 + n0)))
                        if g > gain:
                            best, gain = Condition(name, above, cut), g
        if best is None:
            break
        rule += (best,)
        inside &= best.holds(x)
    return rule


def _prune(rule: Rule, x: dict[str, np.ndarray], bad: np.ndarray) -> Rule:
    """The prefix of conditions with the best (right - wrong) / (right + wrong)."""

    def worth(r: Rule) -> float:
        got = _holds(r, x)
        p, n = (got & bad).sum(), (got & ~bad).sum()
        return (p - n) / (p + n) if p + n else -1.0

    return max((rule[: i + 1] for i in range(len(rule))), key=lambda r: (worth(r), -len(r)), default=())


def learn(x: dict[str, np.ndarray], bad: np.ndarray, seed: int = 7) -> list[Rule]:
    """Ordered rules for bad rows; two thirds of the rows grow a rule, one third prunes it."""
    rules: list[Rule] = []
    if not len(bad) or bad.all() or not bad.any():
        return rules
    part = np.random.default_rng(seed).random(len(bad)) < 2 / 3
    rest = np.ones(len(bad), bool)
    while len(rules) < MOST_RULES:
        g, p = rest & part, rest & ~part
        if (g & bad).sum() < 3:
            break
        rule = _grow({k: v[g] for k, v in x.items()}, bad[g])
        rule = _prune(rule, {k: v[p] for k, v in x.items()}, bad[p])
        got = _holds(rule, x) & rest if rule else np.zeros(len(bad), bool)
        right, wrong = (got & bad & ~part).sum(), (got & ~bad & ~part).sum()
        if not rule or right < 1 or right < LEAST_RIGHT * (right + wrong):
            break
        rules.append(rule)
        rest &= ~got
    return rules


def expression(rules: list[Rule]) -> Column:
    """The decision list as an ordered conditional: false where a rule fires, true if none does."""
    out = None
    for rule in rules:
        fires = F.lit(True)
        for c in rule:
            fires = fires & c.column()
        out = F.when(fires, F.lit(False)) if out is None else out.when(fires, F.lit(False))
    return F.lit(True) if out is None else out.otherwise(F.lit(True))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (F.lit(100) * F.col("n_repeat_words") > F.lit(50) * F.col("n_words"))


def fit(stats: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> list[Rule]:
    known = labels.select("doc_id", F.col("quality").cast("int").alias("quality")).where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull())
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    rows = stats.join(F.broadcast(chosen), "doc_id").where(~base_failed()).select("quality", "doc_id", *(ratio(t, b).alias(n) for n, t, b in RATIOS))
    got = rows.orderBy(F.xxhash64("doc_id"), "doc_id", *(n for n, _, _ in RATIOS)).limit(sample_rows).toPandas().sort_values(["doc_id", *(n for n, _, _ in RATIOS)])  # at most sample_rows rows, also where ids repeat
    return learn({n: got[n].to_numpy(float) for n, _, _ in RATIOS}, (got["quality"] == 0).to_numpy())


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, counts, base_failed, kept: the base rule first, then the learned list."""
    stats = materialise(statistics(docs), "statistics")
    verdict = expression(fit(stats, labels))
    return stats.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & verdict)
