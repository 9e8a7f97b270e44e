"""URL rules decided by a Bloom filter cascade: exact membership of rule keys without a join.

A rule key is host + path. The keys that a url can match are its host's suffixes at label borders, each with a prefix
of its path; only the shapes (labels, path characters) that some rule has can match, so a url has as many keys as the
rules have shapes. All such keys of the corpus are the key universe. Level 1 of the cascade encodes the listed keys,
level 2 the keys of the universe that level 1 takes wrongly, level 3 the listed keys that level 2 takes wrongly, and so
on until a level takes none wrongly. A key is listed if the first level that refuses it is an even one; that is exact for
every key of the universe. Levels are bit arrays that the tasks build in part and that are merged by OR; each is
sized from the count of its keys, and its size is checked before it is broadcast.

Of the rules that fit, the longest key wins (at equal length the longer host). A url that no rule fits is allowed.

Cases: a null url, or one without `://`, has an empty host and path, no rule and the verdict allow; repeated rows are
judged each; an empty table gives an empty result; only page_id and url are read, extra columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, mix64

#: Wrong answers a level may give before the next one mends them, and the bytes a level may have when it is broadcast.
FALSE_RATE, MOST_BYTES = 0.01, 256 << 20
#: Second argument of the second hash.
SALT = 0x5EED


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def key(self) -> str:
        return self.host + self.path


def parse_rules(lines: list[str]) -> list[Rule]:
    """Lines like `block example.net/de/8`: a verdict, and a host with the start of a path."""
    out = []
    for line in lines:
        verdict, _, key = line.partition(" ")
        host, slash, rest = key.partition("/")
        if verdict not in ("allow", "block") or not host:
            raise ValueError(f"not a rule: {line!r}")
        out.append(Rule(verdict, host.lower(), slash + rest))
    if len({r.key for r in out}) < len(out):
        raise ValueError("a key has two rules")
    return out


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lowered) after the first `://` up to `/`, `?`, `#`; path from there up to `?`, `#`."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, url.substr(at + F.lit(3), F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return host, F.regexp_extract(rest, r"(?s)^[^/?#]*(/[^?#]*)?", 1)


def shapes(rules: list[Rule]) -> list[tuple[int, int]]:
    """(labels of the host, characters of the path) of the rules."""
    return sorted({(r.host.count(".") + 1, len(r.path)) for r in rules})


def candidate(host: Column, path: Column, labels: int, chars: int) -> Column:
    """The key of one shape, null where the url is too short for it."""
    fits = (F.size(F.split(host, r"\.")) >= labels) & (F.length(path) >= chars) & (host != "")
    return F.when(fits, F.concat(F.substring_index(host, ".", -labels), F.substring(path, 1, chars)))


class Level:
    """Bits of one Bloom filter; positions by double hashing of two 64-bit hashes, mixed anew with the level's depth.

    Without the depth two keys that meet at one level would meet at every later one of the same size.
    """

    def __init__(self, keys: int, rate: float = FALSE_RATE, depth: int = 1):
        self.depth = np.uint64(depth * 0x9E3779B97F4A7C15 % (1 << 64))
        bits = max(64, math.ceil(-max(keys, 1) * math.log(rate) / math.log(2) ** 2))
        if bits / 8 > MOST_BYTES:
            raise ValueError(f"a level of {bits // 8} bytes is too large to broadcast; raise its false rate or MOST_BYTES")
        self.size = bits
        self.hashes = max(1, round(-math.log2(rate)))
        self.bits = np.zeros((bits + 7) // 8, np.uint8)

    def places(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        k = np.arange(self.hashes, dtype=np.uint64)[:, None]
        a, b = mix64(a.view(np.uint64) + self.depth), mix64(b.view(np.uint64) ^ self.depth)
        return (a + k * (b | np.uint64(1))) % np.uint64(self.size)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        at = self.places(a, b).ravel()
        np.bitwise_or.at(self.bits, (at >> np.uint64(3)).astype(np.int64), (1 << (at & np.uint64(7))).astype(np.uint8))

    def has(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        at = self.places(a, b)
        return ((self.bits[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1).all(axis=0)


def member(levels: list[Level], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether the first level that refuses a key is an even one (levels count from 1)."""
    answer, asked = np.zeros(len(a), bool), np.arange(len(a))
    for i, level in enumerate(levels):
        got = level.has(a[asked], b[asked])
        answer[asked[~got]] = i % 2 == 1
        asked = asked[got]
    answer[asked] = len(levels) % 2 == 1
    return answer


def hashes(key: Column) -> tuple[Column, Column]:
    return F.xxhash64(key), F.xxhash64(key, F.lit(SALT))


def build_cascade(universe: DataFrame, listed: DataFrame, rate: float = FALSE_RATE) -> list[Level]:
    """universe: distinct (a, b) hashes of all corpus keys that are not listed; listed: distinct (a, b) of listed keys.

    Both sides stay distributed; a task sends the bits it sets, and only counts and merged bits reach the driver.
    """
    levels: list[Level] = []
    sides = [listed, universe]
    # Keys of both sides that the levels so far leave undecided.
    while True:
        side = len(levels) % 2
        n = sides[side].count()
        if not n:
            return levels
        level = _merged(sides[side], n, rate, len(levels) + 1)
        levels.append(level)
        other = 1 - side
        sides[other] = materialise(_taken(sides[other], level), f"level{len(levels)}")


def _merged(keys: DataFrame, n: int, rate: float, depth: int) -> Level:
    def run(batches):
        part = Level(n, rate, depth)
        for pdf in batches:
            part.add(pdf["a"].to_numpy(np.int64), pdf["b"].to_numpy(np.int64))
        used = np.flatnonzero(part.bits)
        yield pd.DataFrame({"at": used, "bits": part.bits[used].astype(np.int32)})

    level = Level(n, rate, depth)
    merged = keys.mapInPandas(run, "at long, bits int").groupBy("at").agg(F.bit_or("bits").alias("bits"))
    for part in merged.toLocalIterator():  # as many rows as the level has non-zero bytes, which MOST_BYTES bounds
        level.bits[part["at"]] = part["bits"]
    return level


def _taken(keys: DataFrame, level: Level) -> DataFrame:
    shared = keys.sparkSession.sparkContext.broadcast(level)

    def run(batches):
        for pdf in batches:
            yield pdf[shared.value.has(pdf["a"].to_numpy(np.int64), pdf["b"].to_numpy(np.int64))]

    return keys.mapInPandas(run, "a long, b long")


def judge(pages: DataFrame, rules: list[Rule], rate: float = FALSE_RATE, otherwise: str = "allow") -> DataFrame:
    """page_id, host, path, rule, verdict for every page."""
    spark = pages.sparkSession
    host, path = host_and_path(F.col("url"))
    urls = pages.select("page_id", host.alias("host"), path.alias("path"))
    forms = shapes(rules)
    keys = F.array_compact(F.array(*(candidate(F.col("host"), F.col("path"), *s) for s in forms)))
    a, b = hashes(F.col("key"))
    listed = spark.createDataFrame([(r.key,) for r in rules], "key string")
    listed = listed.select(a.alias("a"), b.alias("b"))
    universe = urls.select(F.explode(keys).alias("key")).where(~F.col("key").isin([r.key for r in rules])).select(a.alias("a"), b.alias("b")).distinct()
    cascade = spark.sparkContext.broadcast(build_cascade(universe, listed, rate))
    verdicts = {r.key: r.verdict for r in rules}

    @F.pandas_udf("boolean")
    def in_list(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(member(cascade.value, x.to_numpy(np.int64), y.to_numpy(np.int64)))

    tried = urls.withColumn("keys", F.array_compact(F.array(*(candidate(F.col("host"), F.col("path"), *s) for s in forms))))
    flags = [F.coalesce(F.get("keys", F.lit(i)), F.lit("")) for i in range(len(forms))]
    found = tried
    for i, key in enumerate(flags):
        found = found.withColumn(f"hit{i}", F.when(key != "", in_list(*hashes(key))))
    hits = F.array(*(F.when(F.col(f"hit{i}"), F.struct(F.length(key).alias("n"), F.length(F.substring_index(key, "/", 1)).alias("h"), key.alias("key"))) for i, key in enumerate(flags)))
    rule = F.array_max(F.array_compact(hits))["key"]
    verdict = F.create_map(*(F.lit(x) for kv in verdicts.items() for x in kv))
    return found.select("page_id", "host", "path", rule.alias("rule")).withColumn("verdict", F.coalesce(F.try_element_at(verdict, F.col("rule")), F.lit(otherwise)))
