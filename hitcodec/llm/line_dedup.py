"""Line dedup: range-partitioned line hashes, streamed in order, give per-document keep bitmaps.

Each line's key (white space stripped, A-Z lower-cased) is hashed to 128 bits. The hashes are range-partitioned and
sorted by (hash, document, position), so that a very common line spreads over many partitions; one pass over a partition
streams each run of a hash and drops the lines of every document but the first. Only the run that a partition begins
with can have its first document in an earlier partition: its lines are written as pending, and settled by a table of the
first document of each partition's first and last hash (two rows a partition, so its size is bounded). The dropped
positions are packed to compressed bitmaps, a row for each document that loses lines; texts are never sorted or sent by
line.

Defined results: a null or empty text is one empty line; keys shorter than `least` code points are never dropped; rows
with the same doc_id are one document for the count of documents; a null doc_id is one document that comes last;
repeated rows each get a row; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hitcodec.llm.common import SPACE, text_key, text_or_empty
from hitcodec.session import materialise

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LAST = np.iinfo(np.int64).max  # stands for a null doc_id


def lines(docs: DataFrame, least: int = 10) -> DataFrame:
    """A row for each line that can be dropped: h1, h2, doc, tk, pos."""
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))
    each = docs.select(doc.alias("doc"), text_key().alias("tk"), F.posexplode(F.split(text_or_empty(), "\n", -1)).alias("pos", "line"))
    key = F.translate(F.btrim("line", F.lit(SPACE)), UPPER, LOWER)
    each = each.select("doc", "tk", "pos", key.alias("key")).where(F.length("key") >= least)
    return each.select(F.xxhash64(F.lit(3), "key").alias("h1"), F.xxhash64("key", F.lit(5)).alias("h2"), "doc", "tk", "pos")


DECIDED = "kind int, h1 long, h2 long, doc long, tk long, pos int"
DROP, PENDING, EDGE = 0, 1, 2


def _stream(batches):
    """Over one sorted partition: dropped lines, pending lines of its first run, and its first documents of two hashes."""
    now = None  # (h1, h2, first doc, is it the partition's first run)
    edges = []
    for batch in batches:
        if not batch.num_rows:
            continue
        h1, h2, doc, tk, pos = (batch.column(i).to_numpy() for i in range(5))
        new = np.empty(len(h1), bool)
        new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        new[0] = now is None or (h1[0], h2[0]) != now[:2]
        start = np.maximum.accumulate(np.where(new, np.arange(len(h1)), -1))
        first = np.where(start >= 0, doc[np.maximum(start, 0)], 0 if now is None else now[2])
        head = np.zeros(len(h1), bool)
        if now is None:
            run = np.flatnonzero(new)
            head[: run[1] if len(run) > 1 else len(h1)] = True
            edges.append((h1[0], h2[0], doc[0]))
        elif now[3]:
            head[: np.argmax(new) if new.any() else len(h1)] = True
        kind = np.where(head, PENDING, DROP)
        out = head | (doc != first)
        now = (h1[-1], h2[-1], first[-1], bool(head[-1]))
        if out.any():
            yield pa.RecordBatch.from_arrays([pa.array(x[out]) for x in (kind.astype(np.int32), h1, h2, doc, tk, pos)], ["kind", "h1", "h2", "doc", "tk", "pos"])
    if now is not None:
        edges += [now[:3]] * (not now[3])
        a = np.array(edges, np.int64)
        zero = np.zeros(len(a), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a), EDGE, np.int32)), pa.array(a[:, 0]), pa.array(a[:, 1]), pa.array(a[:, 2]), pa.array(zero), pa.array(zero.astype(np.int32))], ["kind", "h1", "h2", "doc", "tk", "pos"])


def _bitmap(dropped: pd.Series) -> pd.Series:
    """Positions that go, as a compressed bitmap of those that stay: bit i is line i, whole bytes up to the last one that goes."""

    def one(at):
        keep = np.ones((int(max(at)) // 8 + 1) * 8, bool)
        keep[np.asarray(at)] = False
        return zlib.compress(np.packbits(keep).tobytes(), 6)

    return dropped.map(one)


def keep_bitmaps(docs: DataFrame, least: int = 10) -> DataFrame:
    """doc, tk, keep: for each document that loses lines, its compressed bitmap; lines beyond its bits stay."""
    every = lines(docs, least)
    order = ["h1", "h2", "doc", "tk", "pos"]
    decided = materialise(every.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_stream, DECIDED), "line-decisions")
    # two rows for each partition of the sort: a proven bound
    firsts = decided.where(f"kind = {EDGE}").groupBy("h1", "h2").agg(F.min("doc").alias("first"))
    pending = decided.where(f"kind = {PENDING}").join(F.broadcast(firsts), ["h1", "h2"]).where("doc <> first")
    gone = decided.where(f"kind = {DROP}").select("doc", "tk", "pos").unionByName(pending.select("doc", "tk", "pos"))
    return gone.groupBy("doc", "tk").agg(F.collect_set("pos").alias("dropped")).select("doc", "tk", F.pandas_udf(_bitmap, "binary")("dropped").alias("keep"))


def kept(text: str | None, keep: bytes | None) -> tuple[str, int, int]:
    """Apply a bitmap: the text that stays, lines before, lines dropped."""
    rows = (text or "").split("\n")
    if keep is None:
        return text or "", len(rows), 0
    bits = np.unpackbits(np.frombuffer(zlib.decompress(keep), np.uint8)).astype(bool)[: len(rows)]
    stay = np.ones(len(rows), bool)
    stay[: len(bits)] = bits
    left = [row for row, b in zip(rows, stay.tolist()) if b]
    return "\n".join(left), len(rows), len(rows) - len(left)


def with_bitmaps(docs: DataFrame, least: int = 10) -> DataFrame:
    """Each document's doc_id and text with its bitmap (null: all lines stay)."""
    maps = keep_bitmaps(docs, least).withColumnRenamed("tk", "_tk")
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", doc.alias("doc"), text_key().alias("_tk"))
    return rows.join(maps, ["doc", "_tk"], "left").select("doc_id", "text", "keep")


def line_dedup(docs: DataFrame, least: int = 10) -> DataFrame:
    """doc_id, text (what stays), n_lines, n_dropped."""

    def apply(batches):
        for batch in batches:
            made = [kept(t, k) for t, k in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([m[0] for m in made], pa.string()), pa.array([m[1] for m in made], pa.int64()), pa.array([m[2] for m in made], pa.int64())], ["doc_id", "text", "n_lines", "n_dropped"])

    return with_bitmaps(docs, least).mapInArrow(apply, "doc_id long, text string, n_lines long, n_dropped long")


def line_digest(docs: DataFrame, least: int = 10) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256: of what stays, without sending it on."""

    def apply(batches):
        for batch in batches:
            made = [kept(t, k) for t, k in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
            digest = [hashlib.sha256(m[0].encode()).hexdigest() for m in made]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([m[1] for m in made], pa.int64()), pa.array([m[2] for m in made], pa.int64()), pa.array(digest, pa.string())], ["doc_id", "n_lines", "n_dropped", "kept_sha256"])

    return with_bitmaps(docs, least).mapInArrow(apply, "doc_id long, n_lines long, n_dropped long, kept_sha256 string")
