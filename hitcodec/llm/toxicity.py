"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Features are the n-grams present in the lower-cased text (a space added at both ends), hashed to 2**BITS buckets. Over
all labelled training rows, the log-count ratio of a bucket is r = log(share of toxic rows / share of clean rows that have it),
smoothed by half a row; buckets whose two shares differ by less than `least_z` standard errors get r = 0. A logistic
regression is then fitted on x * r (present or not, times r; the rows scaled to about unit length). The counts are summed in the executors by chunks of buckets, so that what meets
in a task or the driver is bounded by the number of buckets, all of which may be kept; the regression is fitted on at most `fit_rows` labelled
rows (streamed to a file of the driver), half of them toxic where there are enough, and its bias is shifted back to the share of toxic rows overall.

Only text enters a score. Rows whose crc32(doc_id as text) mod 5 is 0 are never learnt from.

Defined results: null and empty texts have no feature and get the score of the bias; null labels and labels without a
document are left out; a document with several labels counts as toxic if one says so; repeated rows each get a score;
without any training row of one class all scores are the share of toxic rows (0 without labels); a null doc_id has no
remainder: it is not held out, is never learnt from, and is scored; a very long text is scored whole, in one task; an
empty table gives an empty result; other columns are kept by `toxicity_filter` and ignored by `score`.
"""

from __future__ import annotations

import tempfile
import zlib
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS = 20
ORDERS = (3, 4, 5, 6)
CHUNK = 16384
PART = 1 << 20
MULTIPLIER = np.uint32(0x01000193)
SPREAD = np.uint32(0x9E3779B1)


def buckets(text: str | None) -> np.ndarray:
    """The bucket of every n-gram of a text, repeats included."""
    if not text:
        return np.zeros(0, np.int32)
    codes = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32)
    found, h = [], codes.copy()
    for n in range(2, min(max(ORDERS), len(codes)) + 1):
        h = h[:-1] * MULTIPLIER + codes[n - 1 :]
        if n in ORDERS:
            mixed = (h ^ (h >> np.uint32(15))) * SPREAD + np.uint32(n * 0x85EBCA6B & 0xFFFFFFFF)
            found.append(((mixed ^ (mixed >> np.uint32(13))) * SPREAD >> np.uint32(32 - BITS)).astype(np.int32))
    return np.concatenate(found)


class Grams:
    """Distinct buckets of a text, without a sort: a stamp table keeps the last place of each bucket."""

    def __init__(self):
        self.stamp = np.zeros(1 << BITS, np.int32)

    def __call__(self, text: str | None) -> np.ndarray:
        every = buckets(text)
        places = np.arange(len(every), dtype=np.int32)
        self.stamp[every] = places
        return every[self.stamp[every] == places]


def held_out(doc_id) -> bool:
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 5 == 0


def known_labels(labels: DataFrame) -> DataFrame:
    """doc_id, y: a label for each document that may be learnt from."""
    known = labels.where("doc_id is not null and toxic is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("y"))
    return known.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0)


def log_ratios(rows: DataFrame, least_z: float = 4.0) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Kept buckets and their log-count ratios over all rows (doc_id, text, y), and the rows of both classes."""

    def count(batches):
        grams, counts, seen = Grams(), np.zeros((2, 1 << BITS), np.uint32), np.zeros(2, np.uint32)
        for batch in batches:
            for text, y in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                counts[int(y > 0), grams(text)] += 1
                seen[int(y > 0)] += 1
        if seen.any():
            for k in range(0, 1 << BITS, CHUNK):
                part = np.concatenate([seen, counts[:, k : k + CHUNK].ravel()])
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([zlib.compress(part.tobytes(), 1)], pa.binary())], ["chunk", "counts"])

    def total(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, part in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                part = np.frombuffer(zlib.decompress(part), np.uint32)
                if k in sums:
                    sums[k] += part
                else:
                    sums[k] = part.astype(np.int64)
        for k, part in sums.items():
            n0, n1 = part[:2].tolist()
            clean, toxic = part[2:].reshape(2, -1)
            bucket, ratio = np.zeros(0, np.int64), np.zeros(0)
            if n0 and n1:
                pool = (clean + toxic) / (n0 + n1)
                error = np.sqrt(pool * (1 - pool) * (1 / n1 + 1 / n0)) + 1e-12
                z = np.abs(toxic / n1 - clean / n0) / error
                bucket = np.flatnonzero((z > least_z) & (clean + toxic > 2))
                ratio = np.log((toxic[bucket] + 0.5) / (n1 + 1)) - np.log((clean[bucket] + 0.5) / (n0 + 1))
            if k == 0:  # the numbers of rows, once
                yield pa.RecordBatch.from_arrays([pa.array([-1, -2], pa.int32()), pa.array([float(n1), float(n0)], pa.float64())], ["bucket", "ratio"])
            yield pa.RecordBatch.from_arrays([pa.array(k + bucket, pa.int32()), pa.array(ratio, pa.float64())], ["bucket", "ratio"])

    kept = rows.mapInArrow(count, "chunk int, counts binary").repartition("chunk").mapInArrow(total, "bucket int, ratio double")
    got = kept.toArrow()  # at most a row for each bucket: 12 MB
    bucket, ratio = got.column(0).to_numpy(), got.column(1).to_numpy()
    seen = dict(zip(bucket[bucket < 0].tolist(), ratio[bucket < 0].astype(int).tolist()))
    order = np.argsort(bucket, kind="stable")[len(seen) :]
    return bucket[order].astype(np.int32), ratio[order], seen.get(-1, 0), seen.get(-2, 0)


def fit_weights(places: np.ndarray, ends: np.ndarray, y: np.ndarray, ratio: np.ndarray, rounds: int = 80, penalty: float = 1e-4) -> tuple[np.ndarray, float]:
    """Logistic regression on present-or-not times ratio, by Adagrad over all rows.

    places: of the kept buckets of all rows, one row after the other (a mapped file), up to `ends`."""
    n = len(ratio)
    sizes = np.diff(ends, prepend=0)
    scale = np.ones(len(y), np.float32)
    cuts = [0, *(np.flatnonzero(np.diff(ends // PART)) + 1).tolist(), len(y)]  # some rows at a time bound the memory

    def parts():
        for k, m in zip(cuts, cuts[1:]):
            flat = np.asarray(places[ends[k] - sizes[k] : ends[m - 1]])
            owner = np.repeat(np.arange(m - k, dtype=np.int32), sizes[k:m])
            yield slice(k, m), flat, owner, ratio[flat].astype(np.float32) * scale[k:m][owner]

    for at, _, owner, x in parts():
        scale[at] = 1 / np.sqrt(np.bincount(owner, x * x, at.stop - at.start) + 1.0)
    w, bias, past, past_bias = np.zeros(n), 0.0, np.full(n, 1e-8), 1e-8
    for _ in range(rounds):
        slope, shift = penalty * w / len(y), 0.0
        for at, flat, owner, x in parts():
            z = np.bincount(owner, w[flat] * x, at.stop - at.start) + bias
            wrong = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[at]) / len(y)
            slope += np.bincount(flat, wrong[owner] * x, n)
            shift += wrong.sum()
        past += slope * slope
        w -= 0.5 * slope / np.sqrt(past)
        past_bias += shift * shift
        bias -= 0.5 * shift / np.sqrt(past_bias)
    return w, float(bias)


def log_odds(share: float) -> float:
    share = min(max(share, 1e-9), 1 - 1e-9)
    return float(np.log(share / (1 - share)))


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = 4000, least_z: float = 4.0) -> dict:
    """The model: kept buckets with their ratios and weights, and the bias.

    fit_rows bounds the labelled rows that the regression sees; the ratios count all of them.
    """
    known = known_labels(labels)
    texts = docs.selectExpr("cast(doc_id as long) as doc_id", "text")
    # the same join at every size: both sides are dealt by doc_id, labels are never broadcast
    kept, ratio, toxic, clean = log_ratios(texts.join(known.hint("merge"), "doc_id").select("doc_id", "text", "y"), least_z)
    bias = log_odds(toxic / max(1, toxic + clean))
    if not len(kept):
        return {"kept": kept, "ratio": ratio, "w": ratio, "bias": bias}

    def places(batches):
        mask = np.zeros(1 << BITS, bool)
        mask[kept] = True
        for batch in batches:
            every = (buckets(t) for t in batch.column(1).to_pylist())
            found = [np.searchsorted(kept, np.unique(e[mask[e]])).astype("<i4").tobytes() for e in every]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(found, pa.binary())], ["doc_id", "y", "found"])

    first = lambda y: known.where(f"y = {y}").orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows // 2)
    sample = F.broadcast(first(1).unionByName(first(0)))  # fit_rows rows of two numbers
    some = texts.join(sample, "doc_id").select("doc_id", "text", "y").mapInArrow(places, "doc_id long, y int, found binary")
    y, sizes = [], []
    with tempfile.TemporaryFile() as file:  # read by the driver alone
        for r in islice(some.orderBy("doc_id", "found").toLocalIterator(), fit_rows):
            y.append(float(r["y"]))
            sizes.append(file.write(r["found"]) // 4)
        file.flush()
        places = np.memmap(file, "<i4", "r") if sum(sizes) else np.zeros(0, np.int32)
        y = np.array(y)
        w, own = fit_weights(places, np.cumsum(sizes), y, ratio)
    return {"kept": kept, "ratio": ratio, "w": w, "bias": own + bias - log_odds(float(y.mean()))}


class Scorer:
    """Scores of texts by a fitted model."""

    def __init__(self, model: dict):
        self.kept, self.bias = np.zeros(1 << BITS, bool), model["bias"]
        self.kept[model["kept"]] = True
        self.at, self.ratio, self.w = model["kept"], model["ratio"], model["w"]

    def __call__(self, text: str | None) -> float:
        every = buckets(text)
        found = np.unique(every[self.kept[every]])
        i = np.searchsorted(self.at, found)
        x = self.ratio[i]
        z = float((x * self.w[i]).sum() / np.sqrt((x * x).sum() + 1.0)) + self.bias
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""

    def apply(batches):
        scorer = Scorer(model)
        for batch in batches:
            scores = [scorer(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([held_out(i) for i in batch.column(0).to_pylist()], pa.bool_()), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.selectExpr("cast(doc_id as long) as doc_id", "text")
    return rows.mapInArrow(apply, "doc_id long, held_out boolean, score double, predicted int")


def toxicity_filter(docs: DataFrame, model: dict, most: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, whose score is below `most`."""
    at = docs.columns.index("text")

    def apply(batches):
        scorer = Scorer(model)
        for batch in batches:
            yield batch.filter(pa.array([scorer(t) < most for t in batch.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(apply, docs.schema)
