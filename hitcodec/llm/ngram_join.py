"""N-gram Jaccard join with Bayesian candidate pruning.

Texts are sets of word 5-grams (lower-cased words; a shorter text is one gram of all its words). Equal sets are one class
(`node`), with its number of copies, so that copies are never paired. Nodes meet in MinHash bands; pairs inside a band's
bucket compare their MinHash values a few at a time and are dropped once the posterior probability (uniform prior,
matches binomial) that their similarity reaches the threshold falls below `tolerance`. What is left makes candidate
components; inside a component all pairs pass the same incremental test, and the rest are verified exactly on their gram
sets. The result has for each document its class (connected by verified links) and its number of links.

Large buckets and components are cut in blocks of nodes, and each pair of blocks is a group of its own: no task holds an
unbounded group, and what a group emits is a row or two for each of its nodes, never its pairs. With `bands` x `rows` =
24 x 5 a pair at the threshold 0.8 fails to meet with probability 7e-5, and less above it.

Defined results: null texts and texts without words have no class mates and no links, and class_id is their doc_id;
a null doc_id has class_id null unless a mate has one; repeated rows are copies, each with its row; an empty table gives
an empty result; other columns are ignored by `ngram_join` and kept by `deduplicate`.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.llm.common import text_key
from hitcodec.session import materialise

GRAM = 5
BANDS, ROWS = 24, 5
HASHES, STEP = 128, 32
BLOCK = 512
WORDS = re.compile(r"\w+")
M1, M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_seeds = np.random.default_rng(20240601)
MUL = (_seeds.integers(0, 1 << 31, HASHES, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
ADD = _seeds.integers(0, 1 << 32, HASHES, dtype=np.uint32)


class _WordHash(dict):
    """Hashes of words, kept up to a bounded number."""

    def __missing__(self, word: str) -> int:
        if len(self) > 400_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def gram_set(text: str | None, words: _WordHash) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's word 5-grams."""
    found = WORDS.findall(text.lower()) if text else []
    if not found:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(words.__getitem__, found), np.uint64, len(found))
    n = min(GRAM, len(w))
    h = np.zeros(len(w) - n + 1, np.uint64)
    for k in range(n):
        h = (h ^ w[k : len(w) - n + 1 + k]) * M1
        h ^= h >> np.uint64(29)
    h *= M2
    return np.unique(h ^ (h >> np.uint64(32)))


def minhash(grams: np.ndarray) -> np.ndarray:
    """HASHES minima of 32 bits."""
    low = (grams >> np.uint64(7)).astype(np.uint32)
    best = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    for k in range(0, len(low), 512):
        x = low[k : k + 512, None] * MUL + ADD
        x ^= x >> np.uint32(15)
        np.minimum(best, (x * np.uint32(0x2C1B3C6D)).min(0), out=best)
    return best


def band_keys(sketch: np.ndarray) -> np.ndarray:
    """A 64-bit key for each band."""
    part = sketch[: BANDS * ROWS].reshape(BANDS, ROWS).astype(np.uint64)
    key = np.arange(1, BANDS + 1, dtype=np.uint64) * M2
    for k in range(ROWS):
        key = (key ^ part[:, k]) * M1
        key ^= key >> np.uint64(31)
    return key.view(np.int64)


def least_matches(threshold: float, tolerance: float) -> list[int]:
    """For each step of STEP values: the fewest matches with posterior P(similarity >= threshold) >= tolerance."""
    found = []
    for n in range(STEP, HASHES + 1, STEP):
        tail = lambda m: sum(math.comb(n + 1, j) * threshold**j * (1 - threshold) ** (n + 1 - j) for j in range(m + 1))
        found.append(next(m for m in range(n + 1) if tail(m) >= tolerance))
    return found


def surviving(left: np.ndarray, right: np.ndarray, same: bool, least: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of two blocks of sketches (16-bit values) that the incremental comparison keeps; i < j if same."""
    hits = np.zeros((len(left), len(right)), np.int16)
    for k in range(STEP):
        hits += left[:, k, None] == right[None, :, k]
    alive = hits >= least[0]
    if same:
        alive &= np.triu(np.ones(alive.shape, bool), 1)
    i, j = np.nonzero(alive)
    count = hits[i, j].astype(np.int32)
    for turn in range(1, len(least)):
        at = slice(turn * STEP, (turn + 1) * STEP)
        count = count + (left[i, at] == right[j, at]).sum(1)
        stay = count >= least[turn]
        i, j, count = i[stay], j[stay], count[stay]
    return i, j


def star_labels(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest index of each one's connected component."""
    label = np.arange(n)
    while len(i):
        old = label.copy()
        low = np.minimum(label[i], label[j])
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        label = label[label]
        if (label == old).all():
            break
    return label


def verify(grams: list[np.ndarray], i: np.ndarray, j: np.ndarray, threshold: float) -> np.ndarray:
    """Which of the index pairs (sorted by i) have Jaccard similarity at least the threshold, exactly."""
    keep = np.zeros(len(i), bool)
    if not len(i):
        return keep
    sizes = np.array([len(g) for g in grams], np.int64)
    _, ids = np.unique(np.concatenate(grams), return_inverse=True)
    starts = np.concatenate([[0], np.cumsum(sizes)])
    flag = np.zeros(ids.max() + 1, np.int32)
    ends = np.flatnonzero(np.diff(i, append=-1)) + 1
    begin = 0
    for end in ends:
        own = ids[starts[i[begin]] : starts[i[begin] + 1]]
        flag[own] = 1
        for k in range(begin, end, 64):  # a few partners at a time bound the memory
            other = j[k : min(k + 64, end)]
            common = np.add.reduceat(flag[np.concatenate([ids[starts[x] : starts[x + 1]] for x in other])], np.concatenate([[0], np.cumsum(sizes[other])[:-1]]))
            keep[k : k + len(other)] = common >= threshold * (len(own) + sizes[other] - common) - 1e-9
        flag[own] = 0
        begin = end
    return keep


class _Forest:
    """Links seen in a task; only those that connect something new are put out. Forgets all beyond a bounded number."""

    def __init__(self):
        self.up: dict[bytes, bytes] = {}

    def root(self, node: bytes) -> bytes:
        while (up := self.up.get(node, node)) != node:
            self.up[node] = node = self.up.get(up, up)
        return node

    def link(self, node: bytes, least: bytes, a: list, b: list) -> None:
        if node == least:
            return
        x, y = self.root(node), self.root(least)
        if x != y:
            if len(self.up) > 500_000:
                self.up.clear()
                x, y = node, least
            self.up[max(x, y)] = min(x, y)
            a.append(max(x, y)), b.append(min(x, y))


def _groups(batches, keys: int):
    """Runs of rows with equal first `keys` columns over sorted batches, as lists of rows."""
    last, rows = None, []
    for batch in batches:
        columns = [c.to_pylist() for c in batch.columns]
        for row in zip(*columns):
            if row[:keys] != last:
                if rows:
                    yield rows
                last, rows = row[:keys], []
            rows.append(row)
    if rows:
        yield rows


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, tk, node (16 bytes of the gram set; null without words), bands, sketch (16-bit values)."""

    def apply(batches):
        words = _WordHash()
        for batch in batches:
            nodes, bands, sketch = [], [], []
            for text in batch.column(2).to_pylist():
                grams = gram_set(text, words)
                if not len(grams):
                    nodes.append(None), bands.append([]), sketch.append(None)
                    continue
                s = minhash(grams)
                nodes.append(xxhash.xxh3_128_digest(grams.tobytes())), bands.append(band_keys(s)), sketch.append(s.astype(np.uint16).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(nodes, pa.binary()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.binary())], ["doc_id", "tk", "node", "bands", "sketch"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tk"), "text")
    return rows.mapInArrow(apply, "doc_id long, tk long, node binary, bands array<long>, sketch binary")


def blocks(rows: DataFrame, group: str, members: str) -> DataFrame:
    """Rows sent to each pair of blocks (x <= y) of their group, in order of node; `members` is the group's size."""
    n = F.ceil(F.col(members) / BLOCK).cast("int")
    at = F.pmod(F.xxhash64(F.lit(5), "node"), n).cast("int")
    rows = rows.withColumn("_at", at).withColumn("_to", F.explode(F.sequence(F.lit(0), n - 1)))
    return rows.withColumn("x", F.least("_at", "_to")).withColumn("y", F.greatest("_at", "_to")).repartition(group, "x", "y").sortWithinPartitions(group, "x", "y", "node")


EDGES = "a binary, b binary"


def candidate_edges(reps: DataFrame, threshold: float, tolerance: float) -> DataFrame:
    """A star of edges for each group of nodes that the pruned comparison connects in a bucket."""
    least = least_matches(threshold, tolerance)
    keys = reps.select(F.explode("bands").alias("bucket"), "node")
    shared = keys.groupBy("bucket").agg(F.count(F.lit(1)).alias("members")).where("members > 1")
    rows = keys.join(shared, "bucket").join(reps.select("node", "sketch"), "node")
    rows = blocks(rows, "bucket", "members").select("bucket", "x", "y", F.col("_at"), "node", "sketch")

    def apply(batches):
        a, b, forest = [], [], _Forest()
        for rows in _groups(batches, 3):
            x, y = rows[0][1], rows[0][2]
            left = [r for r in rows if r[3] == x]
            right = left if x == y else [r for r in rows if r[3] == y]
            if not left or not right or (x == y and len(left) < 2):
                continue
            sig = lambda some: np.frombuffer(b"".join(r[5] for r in some), np.uint16).reshape(-1, HASHES)
            i, j = surviving(sig(left), sig(right), x == y, least)
            nodes = [r[4] for r in left] + ([] if x == y else [r[4] for r in right])
            label = star_labels(len(nodes), i, j if x == y else j + len(left))
            least_node: dict[int, bytes] = {}
            for k, at in enumerate(label.tolist()):
                least_node[at] = min(nodes[k], least_node.get(at, nodes[k]))
            for k, at in enumerate(label.tolist()):
                forest.link(nodes[k], least_node[at], a, b)
            if len(a) > 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary())], ["a", "b"])
                a, b = [], []
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary())], ["a", "b"])

    return rows.mapInArrow(apply, EDGES)


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """node, label (the smallest node of its component): minima over neighbours with pointer jumping, on written tables."""
    both = materialise(edges.union(edges.select("b", "a")).where("a <> b").distinct(), f"{name}-edges")
    labels = materialise(both.groupBy("a").agg(F.min(F.least("a", "b")).alias("label")).withColumnRenamed("a", "node"), name)
    while True:
        near = both.join(labels, both.b == labels.node).select(F.col("a").alias("node"), "label")
        lower = near.union(labels).groupBy("node").agg(F.min("label").alias("low"))
        jump = labels.select(F.col("node").alias("low"), F.col("label").alias("next"))
        new = lower.join(jump, "low").select("node", F.least("low", "next").alias("label"))
        old = labels.withColumnRenamed("label", "old")
        step = materialise(new.join(old, "node"), name)
        labels = step.select("node", "label")
        if not step.where("label <> old").limit(1).count():
            return labels


def verified(docs: DataFrame, reps: DataFrame, parts: DataFrame, threshold: float, tolerance: float) -> DataFrame:
    """node, mate (a node it is connected to in its blocks, or itself), links (documents linked to, other classes)."""
    least = least_matches(threshold, tolerance)
    sizes = parts.groupBy("label").agg(F.count(F.lit(1)).alias("members"))
    wanted = parts.join(sizes, "label").join(reps.select("node", "copies", "rep"), "node")
    wanted = wanted.select("label", "members", "node", "copies", F.col("rep.doc_id").alias("_d"), F.col("rep.tk").alias("_t"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tk"), "text")
    rows = wanted.join(texts, F.expr("_d <=> doc_id and _t = tk")).select("label", "members", "node", "copies", "text")

    def shingle(batches):
        words = _WordHash()
        for batch in batches:
            grams = [gram_set(t, words) for t in batch.column(4).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array([minhash(g).astype(np.uint16).tobytes() for g in grams], pa.binary()), pa.array([g.tobytes() for g in grams], pa.binary())], ["label", "members", "node", "copies", "sketch", "grams"])

    rows = rows.mapInArrow(shingle, "label binary, members long, node binary, copies long, sketch binary, grams binary")
    rows = blocks(rows, "label", "members").select("label", "x", "y", "_at", "node", "copies", "sketch", "grams")

    def apply(batches):
        for rows in _groups(batches, 3):
            x, y = rows[0][1], rows[0][2]
            rows = list({r[4]: r for r in rows}.values())  # a node once, though rows of its document repeat
            left = [r for r in rows if r[3] == x]
            right = left if x == y else [r for r in rows if r[3] == y]
            if not left or not right:
                continue
            sig = lambda some: np.frombuffer(b"".join(r[6] for r in some), np.uint16).reshape(-1, HASHES)
            i, j = surviving(sig(left), sig(right), x == y, least)
            every = left if x == y else left + right
            j = j if x == y else j + len(left)
            kept = verify([np.frombuffer(r[7], np.uint64) for r in every], i, j, threshold)
            i, j = i[kept], j[kept]
            copies = np.array([r[5] for r in every], np.int64)
            links = np.zeros(len(every), np.int64)
            np.add.at(links, i, copies[j])
            np.add.at(links, j, copies[i])
            label = star_labels(len(every), i, j)
            some = np.flatnonzero(links)
            yield pa.RecordBatch.from_arrays([pa.array([every[k][4] for k in some], pa.binary()), pa.array([every[label[k]][4] for k in some], pa.binary()), pa.array(links[some], pa.int64())], ["node", "mate", "links"])

    return rows.mapInArrow(apply, "node binary, mate binary, links long")


def classes(docs: DataFrame, threshold: float = 0.8, tolerance: float = 1e-4) -> DataFrame:
    """doc_id, tk, node, label (of the class; null without words), links."""
    drawn = materialise(sketches(docs), "sketches")
    rep = F.min(F.struct(F.coalesce("doc_id", F.lit(2**63 - 1)).alias("order"), "doc_id", "tk")).alias("rep")
    reps = materialise(
        drawn.where("node is not null").groupBy("node").agg(F.count(F.lit(1)).alias("copies"), rep, F.first("bands").alias("bands"), F.first("sketch").alias("sketch")),
        "nodes",
    )
    found = materialise(candidate_edges(reps, threshold, tolerance).distinct(), "candidates")
    checked = materialise(verified(docs, reps, components(found, "candidate-components"), threshold, tolerance), "verified")
    joined = components(checked.select(F.col("node").alias("a"), F.col("mate").alias("b")), "classes")
    links = checked.groupBy("node").agg(F.sum("links").alias("links"))
    nodes = reps.select("node", "copies").join(links, "node", "left").join(joined, "node", "left")
    nodes = nodes.select("node", F.coalesce("label", "node").alias("label"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"))
    return drawn.select("doc_id", "tk", "node").join(nodes, "node", "left")


def ngram_join(docs: DataFrame, threshold: float = 0.8, tolerance: float = 1e-4) -> DataFrame:
    """doc_id, class_id (the smallest doc_id of its class), n_links (documents of similarity >= threshold)."""
    rows = materialise(classes(docs, threshold, tolerance), "members")
    least = rows.where("label is not null").groupBy("label").agg(F.min("doc_id").alias("class_id"))
    rows = rows.join(least, "label", "left")
    return rows.select("doc_id", F.when(F.col("label").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("links", F.lit(0)).cast("long").alias("n_links"))


def deduplicate(docs: DataFrame, threshold: float = 0.8, tolerance: float = 1e-4) -> DataFrame:
    """The rows of docs, all columns: of each class the one of the smallest doc_id (then text key); all without words."""
    rows = materialise(classes(docs, threshold, tolerance), "members")
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tk")
    keep = rows.where("label is not null").groupBy("label").agg(F.min(order).alias("k")).select(F.col("k.doc_id").alias("_kd"), F.col("k.tk").alias("_kt"), F.lit(True).alias("_one"))
    free = rows.where("label is null").select(F.col("doc_id").alias("_kd"), F.col("tk").alias("_kt"), F.lit(False).alias("_one")).distinct()
    texts = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("_d"), text_key().alias("_t"))
    # a null text has a null-free key, so that the pair (doc_id, key) names every row
    both = texts.join(keep.union(free), F.col("_d").eqNullSafe(F.col("_kd")) & (F.col("_t") == F.col("_kt")))
    same = Window.partitionBy("_d", "_t").orderBy("_t")
    return both.withColumn("_n", F.row_number().over(same)).where("_n = 1 or not _one").select("row.*")
