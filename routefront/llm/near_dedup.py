"""Near-duplicate classes by consistent weighted sampling of TF-IDF shingles.

Texts with equal words are one node. A node's elements are its shingles of five words (a shorter text is one shingle),
weighted by term frequency times inverse document frequency. Improved consistent weighted sampling draws `SAMPLES`
elements a node, so that two nodes draw the same one with a probability equal to their weighted Jaccard similarity;
`ROWS` samples make a band, and nodes that share a band share a bucket.

A bucket is not turned into pairs. Its most central node (the one with the largest buckets) is its leader, and the
members are verified against the leader on their whole texts: exact weighted Jaccard similarity of at least `SIMILAR`.
Links join nodes to classes. A bucket is done once all its nodes are in one class. Elsewhere the outsiders, the nodes
beside a bucket's largest class, are compared with all members, block by block, on whole vectors; only pairs whose
samples agree often enough and whose classes are still apart are computed, so a task returns links and no pairs. The
outsiders of a bucket that has very many are dealt into parts, which are compared beside each other: there is one such
round, however large a bucket is. Nothing is capped.

Every shingle's weight is its count times idf = (log(1 + 1/share) / log(1 + 1/FLOOR)) ** DAMP, where share is the part of all
documents that have it, `FLOOR` at least: up to that, or in one document only, a shingle is rare and weighs 1. The power keeps a large group of near
copies together, whose own shingles are frequent because of it. Shares above the floor count every document: each task
first counts its shingles in groups of documents and sends those in at least `REPORT` of a group; a group that does not
send a shingle has it in less than that share, which bounds its frequency from above. Shingles that may reach the floor,
at most (mean shingles a document) / (FLOOR - REPORT), are then counted in every document.

Cases: null, empty and wordless texts have equal (no) words and form one class; ties and repeated rows are members
like others, and one row of a class, with the smallest doc_id, is kept; a null doc_id comes after all others; an empty
table gives an empty result; only doc_id and text are read, and `deduplicate` passes all columns through.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_texts, materialise, mix64, mix_into, slices, text_views, token_bounds, token_hashes, words_hash

SHINGLE, SIMILAR = 5, 0.8
BANDS, ROWS = 10, 3
SAMPLES = BANDS * ROWS
#: Share of documents up to which a shingle counts as rare, power of the inverse document frequency, least share of a group of documents that a task sends, documents and shingles of a group.
FLOOR, DAMP, REPORT, GROUP, HELD = 0.01, 0.25, 0.005, 4096, 2_000_000
#: Agreeing samples below which a pair is not verified: at similarity 0.8 a pair has fewer once in 19,000 (binomial of 30 draws).
LEAST_AGREE = 15
#: Nodes of a bucket outside its largest class that are compared with its members in one task, and members of a block of that comparison.
OUTSIDERS, BLOCK = 1024, 2048
#: Elements that are drawn from at a time, so that the numbers stay in a core's cache.
DRAWN = 1 << 15
#: Share of all rows above which a class is settled on the map side; at most 1/SUPPORT classes are broadcast.
SUPPORT = 0.0005

_SPREAD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]
_SEEDS = mix64(np.arange(1, SAMPLES + 1, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019))


def shingles(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles of every document: document, 64-bit hash, count; sorted by document and hash."""
    starts, ends, doc = token_bounds(buf, offs)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    h = token_hashes(buf, starts, ends)
    size = np.bincount(doc, minlength=len(offs) - 1)
    end, nth = np.cumsum(size)[doc], np.arange(len(h))
    whole = nth + SHINGLE <= end
    whole |= (nth + size[doc] == end) & (size[doc] < SHINGLE)  # a short text is one shingle
    at = np.flatnonzero(whole)
    end = end[at]
    short = np.flatnonzero(at + SHINGLE > end)
    after = np.append(h, np.zeros(SHINGLE, np.uint64))
    mixed, temp = np.zeros(len(at), np.uint64), np.empty(len(at), np.uint64)
    for k in range(SHINGLE):
        word = after[at + k]
        word[short[at[short] + k >= end[short]]] = 0
        word *= _SPREAD[k]
        mixed += word
        mix_into(mixed, temp)
    owner = doc[at]
    order = np.argsort(mixed)
    few = owner.astype(np.uint16) if len(offs) <= 1 << 16 else owner  # 16-bit keys are sorted by counting
    order = order[np.argsort(few[order], kind="stable")]
    owner, mixed = owner[order], mixed[order]
    new = np.ones(len(owner), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (mixed[1:] != mixed[:-1])
    begin = np.flatnonzero(new)
    return owner[begin], mixed[begin], np.diff(np.append(begin, len(owner)))


class Weights:
    """Inverse document frequency of the shingles above the floor (sorted), 1 for all others."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        order = np.argsort(keys)
        self.keys, self.values = keys[order], values[order]

    def of(self, shingle: np.ndarray, count: np.ndarray) -> np.ndarray:
        w = count.astype(float)
        if len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, shingle), len(self.keys) - 1)
            w *= np.where(self.keys[at] == shingle, self.values[at], 1.0)
        return w


def document_weights(docs: DataFrame) -> Weights:
    def run(batches):
        keys: list[np.ndarray] = []
        n = held = 0

        def send():
            k, c = np.unique(np.concatenate(keys), return_counts=True)
            hit = c >= REPORT * n
            return pa.RecordBatch.from_arrays([pa.array(k[hit].view(np.int64)), pa.array(c[hit]), pa.array(np.full(hit.sum(), n))], ["shingle", "n", "docs"])

        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                keys.append(shingles(*text_views(part.column(0)))[1])
                n += part.num_rows
                held += len(keys[-1])
                if n >= GROUP or held >= HELD:
                    yield send()
                    keys, n, held = [], 0, 0
        if keys and n:
            yield send()

    total = docs.count()
    least = max(FLOOR * total, 1.0)
    sums = docs.select("text").mapInArrow(run, "shingle long, n long, docs long").groupBy("shingle").agg(F.sum("n").alias("n"), F.sum("docs").alias("docs"))
    likely = sums.where(F.col("n") + REPORT * (total - F.col("docs")) > F.lit(least)).select("shingle").toArrow()  # at most mean shingles / (FLOOR - REPORT)
    if not likely.num_rows:
        return Weights(np.zeros(0, np.uint64), np.zeros(0))
    shared = docs.sparkSession.sparkContext.broadcast(np.sort(likely.column("shingle").to_numpy().view(np.uint64)))

    def count(batches):
        keys = shared.value
        n = np.zeros(len(keys), np.int64)
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                found = shingles(*text_views(part.column(0)))[1]
                at = np.minimum(np.searchsorted(keys, found), len(keys) - 1)
                n += np.bincount(at[keys[at] == found], minlength=len(keys))
        hit = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(keys[hit].view(np.int64)), pa.array(n[hit])], ["shingle", "n"])

    rows = docs.select("text").mapInArrow(count, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") > F.lit(least)).collect()  # at most mean shingles / FLOOR
    df = np.array([r["n"] for r in rows], float) / total
    return Weights(np.array([r["shingle"] for r in rows], np.int64).view(np.uint64), (np.log1p(1 / df) / np.log1p(1 / FLOOR)) ** DAMP if len(rows) else df)


def sample(owner: np.ndarray, shingle: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Documents that have elements, and their samples (documents, SAMPLES): hashes of element and quantised weight. Whole documents, about `DRAWN` elements at a time."""
    begin = np.flatnonzero(np.append(True, owner[1:] != owner[:-1])) if len(owner) else np.zeros(0, np.int64)
    out = np.zeros((len(begin), SAMPLES), np.uint64)
    ends = np.append(begin[1:], len(owner))
    i = 0
    while i < len(begin):
        j = max(i + 1, int(np.searchsorted(ends, begin[i] + DRAWN, "right")))
        part = slice(begin[i], ends[j - 1])
        _draw(begin[i:j] - begin[i], shingle[part], weight[part], out[i:j])
        i = j
    return owner[begin], out


def _draw(begin: np.ndarray, shingle: np.ndarray, weight: np.ndarray, out: np.ndarray) -> None:
    """Samples of documents that begin at `begin`, into out."""
    rank = np.repeat(np.arange(len(begin)), np.diff(np.append(begin, len(shingle))))
    log_w = np.log(weight).astype(np.float32)
    low, unit = np.uint64((1 << 21) - 1), np.float32(1 / (1 << 21))
    a, b, temp = (np.empty(len(shingle), np.uint64) for _ in range(3))

    def uniform(x: np.ndarray, bit: int) -> np.ndarray:
        np.right_shift(x, np.uint64(bit), out=temp)
        np.bitwise_and(temp, low, out=temp)
        u = temp.view(np.int64).astype(np.float32)
        u *= unit
        u += unit / 2
        return u

    def gamma(u: np.ndarray, v: np.ndarray) -> np.ndarray:
        u *= v
        return np.negative(np.log(u, out=u), out=u)

    for k in range(SAMPLES):
        mix_into(np.bitwise_xor(shingle, _SEEDS[k], out=a), temp)
        mix_into(np.add(a, _SPREAD[0], out=b), temp)
        r, c, beta = gamma(uniform(a, 0), uniform(a, 21)), gamma(uniform(a, 42), uniform(b, 0)), uniform(b, 21)
        t = np.floor(log_w / r + beta)
        value = np.log(c, out=c)
        value -= r * (t - beta + 1)
        hit = np.flatnonzero(value == np.minimum.reduceat(value, begin)[rank])
        hit = hit[np.append(True, rank[hit[1:]] != rank[hit[:-1]])]
        out[:, k] = mix64(shingle[hit] + t[hit].astype(np.int64).view(np.uint64) * _SPREAD[1])


SIGNED = "row long, doc_id long, node long, bands array<long>, prints binary"


def signatures(docs: DataFrame, weights) -> DataFrame:
    """Per document: its node, band keys, and 16 bits of every sample (null without words)."""

    def run(batches):
        task, n = TaskContext.get().partitionId() << 33, 0
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                size = part.num_rows
                owner, key, count = shingles(*text_views(part.column(1)))
                docs_, s = sample(owner, key, weights.value.of(key, count))
                bands: list = [None] * size
                prints: list = [None] * size
                keys = np.zeros((len(docs_), BANDS), np.uint64)
                for b in range(BANDS):
                    for i in range(ROWS):
                        keys[:, b] = mix64(keys[:, b] * _SPREAD[2] + s[:, b * ROWS + i] + np.uint64(b))
                short = (s & np.uint64(0xFFFF)).astype(np.uint16)
                for j, d in enumerate(docs_.tolist()):
                    bands[d], prints[d] = keys[j].view(np.int64), short[j].tobytes()
                rows = np.arange(n, n + size) + task
                n += size
                yield pa.RecordBatch.from_arrays([pa.array(rows), part.column(0), part.column(2), pa.array(bands, pa.list_(pa.int64())), pa.array(prints, pa.binary())], ["row", "doc_id", "node", "bands", "prints"])

    return docs.select("doc_id", "text", words_hash(F.col("text")).alias("node")).mapInArrow(run, SIGNED)


def print_rows(prints: pa.Array) -> np.ndarray:
    """Samples of each node, a row each."""
    return np.frombuffer(b"".join(prints.to_pylist()), np.uint16).reshape(len(prints), SAMPLES)


def _likely(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Pairs (a, b) whose samples agree often enough."""

    @F.arrow_udf("int")
    def agree(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array((print_rows(a) == print_rows(b)).sum(1), pa.int32())

    side = lambda c: nodes.select(F.col("node").alias(c), F.col("prints").alias(f"p{c}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").where(agree("pa", "pb") >= LEAST_AGREE).select("a", "b")


def _verified(pairs: DataFrame, texts: DataFrame, weights) -> DataFrame:
    """Pairs with the exact weighted Jaccard similarity of their whole texts."""

    def run(batches):
        cached: dict = {}

        def vector(node: int, text: str):
            if node not in cached:
                if len(cached) > 64:
                    cached.clear()
                _, key, count = shingles(*text_views(pa.array([text], pa.large_string())))
                cached[node] = (key, weights.value.of(key, count))
            return cached[node]

        for batch in batches:
            for k in range(0, batch.num_rows, 64):
                part = batch.slice(k, 64)
                out = [similarity(*vector(a, x), *vector(b, y)) for a, b, x, y in zip(*(c.to_pylist() for c in part.columns), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(out, pa.float64())], ["a", "b", "similarity"])

    side = lambda c: texts.select(F.col("node").alias(c), F.col("text").alias(f"t{c}")).hint("merge")
    return pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long, similarity double")


def components(links: DataFrame, label: str = "components") -> DataFrame:
    """node, class (smallest node of the connected component) for every node that has a link."""
    both = materialise(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), f"{label}-edges")
    now = materialise(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("a")).alias("class")), f"{label}-0")
    for k in range(1, 200):
        near = both.join(now.select(F.col("node").alias("b"), "class"), "b").groupBy(F.col("a").alias("node")).agg(F.min("class").alias("least"))
        step = now.join(near, "node").select("node", F.least("class", "least").alias("class"), F.col("class").alias("old"))
        jump = now.select(F.col("node").alias("class"), F.col("class").alias("up"))
        after = materialise(step.join(jump, "class").select("node", F.least("class", "up").alias("class"), "old"), f"{label}-{k}")
        if not after.where(F.col("class") != F.col("old")).limit(1).count():
            return after.select("node", "class")
        now = after.select("node", "class")
    raise RuntimeError("components did not settle")


def _vectors(texts: DataFrame, weights) -> DataFrame:
    """node, keys (its shingles, sorted), weights: whole vectors of the nodes that are compared inside buckets."""

    def fn(batch: pa.RecordBatch):
        owner, key, count = shingles(*text_views(batch.column(1)))
        w = weights.value.of(key, count)
        cut = np.searchsorted(owner, np.arange(batch.num_rows + 1))
        spans = list(zip(cut[:-1], cut[1:], strict=True))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([key[i:j].tobytes() for i, j in spans], pa.binary()), pa.array([w[i:j].tobytes() for i, j in spans], pa.binary())], ["node", "keys", "weights"])

    return map_texts(texts, ["node", "text"], fn, "node long, keys binary, weights binary")


def similarity(ka: np.ndarray, wa: np.ndarray, kb: np.ndarray, wb: np.ndarray) -> float:
    """Weighted Jaccard similarity of two vectors with sorted keys."""
    _, i, j = np.intersect1d(ka, kb, True, True)
    least, most = np.minimum(wa[i], wb[j]).sum(), np.maximum(wa[i], wb[j]).sum()
    union = wa.sum() - wa[i].sum() + wb.sum() - wb[j].sum() + most
    return float(least / union) if union else 1.0


def _settled(rows: DataFrame) -> DataFrame:
    """Links inside (bucket, part, block): each outsider against every member of another class, until it is in that class."""

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by("node").combine_chunks()
        x = print_rows(group.column("prints"))
        node, out = group.column("node").to_numpy(), group.column("outside").to_numpy()
        first_block = not group.column("block").to_numpy().any()
        keys = [np.frombuffer(k.as_buffer(), np.uint64) for k in group.column("keys")]
        w = [np.frombuffer(k.as_buffer(), np.float64) for k in group.column("weights")]
        codes, cls = np.unique(group.column("class").to_numpy(), return_inverse=True)
        parent = list(range(len(codes)))

        def find(c: int) -> int:
            while parent[c] != c:
                parent[c] = parent[parent[c]]
                c = parent[c]
            return c

        links = []
        for i in np.flatnonzero(out).tolist():
            agree = (x == x[i]).sum(1)
            # outsiders meet each other once, in the first block
            likely = np.flatnonzero((agree >= LEAST_AGREE) & (cls != cls[i]) & (~out | ((np.arange(len(x)) > i) & first_block)))
            for j in likely[np.argsort(-agree[likely], kind="stable")].tolist():
                p, q = find(int(cls[i])), find(int(cls[j]))
                if p != q and similarity(keys[i], w[i], keys[j], w[j]) >= SIMILAR:
                    parent[q] = p
                    links.append((node[i], node[j]))
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return rows.groupBy("bucket", "part", "block").applyInArrow(run, "a long, b long")


def _dealt(state: DataFrame) -> DataFrame:
    """(bucket, part, block, node, class, outside): every outsider meets every member of its bucket once.

    The outsiders are dealt into parts and all nodes into blocks. A part's outsiders go to all blocks; the other nodes go
    to their own block, those beside them of the main class for every part, other outsiders for the parts before theirs.
    """
    parts, blocks = (F.ceil(F.col(c) / k).cast("int") for c, k in (("outsiders", OUTSIDERS), ("size", BLOCK)))
    state = state.withColumns({"parts": parts, "blocks": blocks, "outsider": F.col("class") != F.col("main")})
    state = state.withColumns({"part": F.pmod(F.xxhash64("node", F.lit(1)), "parts").cast("int"), "block": F.pmod(F.xxhash64("node"), "blocks").cast("int")})
    one = lambda part, block, outside: F.struct(part.alias("part"), block.alias("block"), F.lit(outside).alias("outside"))
    own = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda b: one(F.col("part"), b, True))
    upto = F.when(F.col("outsider"), F.col("part")).otherwise(F.col("parts"))  # parts that meet the node as a member
    member = F.transform(F.filter(F.sequence(F.lit(0), F.col("parts") - 1), lambda p: p < upto), lambda p: one(p, F.col("block"), False))
    places = F.when(F.col("outsider"), F.concat(own, member)).otherwise(member)
    return state.select("bucket", "node", "class", F.explode(places).alias("to")).select("bucket", "node", "class", "to.*")


def classes(docs: DataFrame) -> DataFrame:
    """Per document: row, doc_id, node, class_id (smallest doc_id of its class), class_size, kept."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    weights = spark.sparkContext.broadcast(document_weights(docs))
    signed = materialise(signatures(docs, weights), "signatures")
    nodes = materialise(signed.where(F.col("bands").isNotNull()).groupBy("node").agg(F.first("bands").alias("bands"), F.first("prints").alias("prints")), "nodes")
    found = nodes.select("node", F.explode("bands").alias("bucket"))
    shared = found.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > 1)
    rows = materialise(found.join(shared, "bucket"), "buckets")  # only buckets of two nodes or more
    central = rows.groupBy("node").agg(F.sum("size").alias("central"))
    rows = materialise(rows.join(central, "node"), "ranked")
    leaders = rows.groupBy("bucket").agg(F.max(F.struct("central", "node"))["node"].alias("a"))
    pairs = rows.join(leaders, "bucket").where(F.col("a") != F.col("node")).select("a", F.col("node").alias("b"))
    pairs = _ordered(pairs).distinct()
    done = materialise(_likely(pairs, nodes), "pairs-0")
    needed = rows.select("node").distinct()

    texts = materialise(_named(docs).join(needed.hint("merge"), "node", "left_semi").dropDuplicates(["node"]), "texts")
    links = materialise(_verified(done, texts, weights).where(F.col("similarity") >= SIMILAR), "links-0")
    label = components(links, "classes-1")
    placed = rows.select("bucket", "node").join(label, "node", "left").withColumn("class", F.coalesce("class", "node"))
    per = placed.groupBy("bucket", "class").agg(F.count(F.lit(1)).alias("n"))
    mixed = per.groupBy("bucket").agg(F.sum("n").alias("size"), F.max(F.struct("n", "class")).alias("main")).where(F.col("size") > F.col("main.n"))
    mixed = materialise(mixed.select("bucket", "size", F.col("main.class").alias("main"), (F.col("size") - F.col("main.n")).alias("outsiders")), "mixed")
    if mixed.limit(1).count():
        dealt = _dealt(placed.join(mixed, "bucket"))
        vectors = _vectors(texts.join(dealt.select("node").distinct().hint("merge"), "node", "left_semi"), weights).join(nodes.select("node", "prints"), "node")
        links = materialise(links.select("a", "b").unionByName(_settled(dealt.join(vectors, "node"))), "links-1")
        label = components(links, "classes-last")
    placed = materialise(signed.select("row", "doc_id", "node").join(label, "node", "left").withColumn("class", F.coalesce("class", "node")), "placed")
    first = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "row")
    heads = materialise(placed.groupBy("class").agg(F.min(first).alias("head"), F.count(F.lit(1)).alias("class_size")), "heads")
    # a class that a large share of the rows is in is no key of a shuffle: its head is broadcast
    large = F.col("class_size") > F.lit(SUPPORT) * F.lit(placed.count())
    rest = placed.join(F.broadcast(heads.where(large).select("class")), "class", "left_anti").join(heads.where(~large).hint("merge"), "class")
    found = placed.join(F.broadcast(heads.where(large)), "class").unionByName(rest)
    return found.select("row", "doc_id", "node", F.col("head.doc_id").alias("class_id"), "class_size", (F.col("row") == F.col("head.row")).alias("kept"))


def _named(docs: DataFrame) -> DataFrame:
    """node and text of every row."""
    return docs.select(words_hash(F.col("text")).alias("node"), F.coalesce("text", F.lit("")).alias("text"))


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def deduplicate(docs: DataFrame) -> DataFrame:
    """docs with one row of every class, all columns."""
    kept = materialise(classes(docs).where("kept").select(F.col("doc_id").alias("__rf_doc"), F.col("node").alias("__rf_node")), "kept")

    own = docs.withColumn("__rf_own", words_hash(F.col("text")))
    same = own["doc_id"].cast("long").eqNullSafe(kept["__rf_doc"]) & (own["__rf_own"] == kept["__rf_node"])
    once = Window.partitionBy("doc_id", "__rf_own").orderBy("doc_id")  # rows repeated whole
    return own.join(kept, same, "left_semi").withColumn("__rf_rank", F.row_number().over(once)).where("__rf_rank = 1").select(*docs.columns)
