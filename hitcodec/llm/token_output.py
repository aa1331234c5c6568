"""Token-ID output: documents as token ids in range-coded frames.

Documents are range-partitioned by doc_id and sorted; each partition streams its ids into frames of at least
`frame_ids` ids that end with a document, a row each in a Parquet table (the file format): partition, frame, the frame's
bytes, and the doc_ids and lengths of its documents. Frames are read back on their own, in any order, and split again.

With a byte-level vocabulary, texts are cut where it cuts anyway (before ASCII white space that follows other
characters, and between an ASCII letter and a mark of ",.:;?!"); Arrow makes a dictionary of a run's pieces, and each distinct piece is encoded by the tokenizers library
once and kept in a bounded cache. Texts that hold one of the vocabulary's special tokens literally, and all texts under other
vocabularies, are encoded whole, so that ids are always those of the library with add_special_tokens=False.

Defined results: null text is empty and has only the end id; a null doc_id comes first; rows of equal doc_id are ordered
by text and keep a row each; a very long text is one document of one frame, which it may exceed (a frame's bytes are held
by one task); an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.llm.token_codec import decode_ids, encode_ids
from hitcodec.session import scratch

END = 0
MOST_PIECES, JOINED = 1 << 21, 500  # pieces kept (some 30 bytes each); pieces encoded in a row
RUN = 16 << 20  # bytes of text taken together
# The white space of ASCII, and the other characters of Unicode's White_Space.
SPACES = {b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r"}
ASCII_SPACE = np.isin(np.arange(256), [ord(c) for c in SPACES])
OTHER_SPACE = ["\x85", "\xa0", "\u1680", "\u2000", "\u2001", "\u2002", "\u2003", "\u2004", "\u2005", "\u2006", "\u2007", "\u2008", "\u2009", "\u200a", "\u2028", "\u2029", "\u202f", "\u205f", "\u3000"]


class Pieces:
    """Ids of text pieces by a tokenizer, kept as Arrow and NumPy arrays; what is missing is encoded in batches."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.vocabulary = self.tokenizer.get_vocab_size()
        with open(path, encoding="utf-8") as file:
            kind = json.load(file)
        cuts = kind.get("pre_tokenizer") or {}
        plain = cuts.get("type") == "ByteLevel" and cuts.get("use_regex") and not cuts.get("add_prefix_space")
        self.cuttable = bool(plain) and not kind.get("normalizer") and not kind.get("truncation") and not kind.get("padding")
        self.special = [t["content"] for t in kind.get("added_tokens") or [] if t["content"]]
        if self.cuttable:  # bytes of each id, by the one character that byte-level vocabularies have for a byte
            self.bytes_of = np.zeros(self.vocabulary, np.int64)
            for token, k in self.tokenizer.get_vocab().items():
                self.bytes_of[k] = len(token)
        self.forget()

    def forget(self) -> None:
        self.known, self.ids, self.begins, self.sizes = pa.array([], pa.large_binary()), np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def look(self, pieces: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct pieces, and how many each has."""
        if len(self.known) > MOST_PIECES or len(self.ids) > 4 * MOST_PIECES:
            self.forget()
        found = pc.index_in(pieces, self.known)
        missing = found.is_null().to_numpy(zero_copy_only=False)
        at = pc.fill_null(found, 0).to_numpy()
        if missing.any():
            new = pieces.filter(pa.array(missing))
            ids, sizes = self.fresh(new)
            at = np.where(missing, len(self.known) + np.cumsum(missing) - 1, at)
            self.begins = np.append(self.begins, np.cumsum(sizes) - sizes + len(self.ids))
            self.sizes, self.ids = np.append(self.sizes, sizes), np.append(self.ids, ids)
            self.known = pa.concat_arrays([self.known, new])
        sizes = self.sizes[at]
        return _spread(self.ids, self.begins[at], sizes), sizes

    def fresh(self, pieces: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct pieces, and how many each has. Those that begin with a space and end otherwise are encoded many in a row."""
        data, ends = _bytes(pieces)
        first, last = data[ends[:-1]], data[ends[1:] - 1]
        in_row = ASCII_SPACE[first] & ~ASCII_SPACE[last]
        for k in np.flatnonzero(in_row & (last >= 128)).tolist():
            in_row[k] = pieces[k].as_py().decode()[-1] not in OTHER_SPACE
        alone = [p.decode() for p in pieces.filter(pa.array(~in_row)).to_pylist()]
        parts = self.whole(alone)
        sizes = [len(p) for p in parts]
        data, ends = _bytes(pieces.filter(pa.array(in_row)))
        for k in range(0, len(ends) - 1, JOINED):
            some = ends[k : k + JOINED + 1]
            parts += self.whole([data[some[0] : some[-1]].tobytes().decode()])
            stops = np.searchsorted(np.cumsum(self.bytes_of[parts[-1]]), some[1:] - some[0]) + 1
            sizes.extend(np.diff(stops, prepend=0).tolist())
        # back in the order asked for
        ids, sizes = np.concatenate([np.zeros(0, np.uint32), *parts]), np.array(sizes, np.int64)
        begins = np.cumsum(sizes) - sizes
        back = np.argsort(np.concatenate([np.flatnonzero(~in_row), np.flatnonzero(in_row)]))
        return _spread(ids, begins[back], sizes[back]), sizes[back]

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of some texts, each with the end id, and how many each has."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        if not self.cuttable:
            return _joined([np.append(ids, np.uint32(END)) for ids in self.whole(texts.to_pylist())])
        special = np.zeros(len(texts), bool)
        for token in self.special:
            special |= pc.match_substring(texts, token).to_numpy(zero_copy_only=False)
        if special.any():
            return self._mixed(texts, special)
        data, ends = _bytes(texts)
        starts, pieces = _cut(data, ends)
        pieces = pieces.dictionary_encode()
        ids, sizes = self.look(pieces.dictionary)
        begins = (np.cumsum(sizes) - sizes).astype(np.int32)
        # the end id is a piece of its own behind each text
        index = np.insert(pieces.indices.to_numpy(), np.searchsorted(starts, ends[1:]), len(sizes))
        begins, sizes = np.append(begins, np.int32(len(ids))).take(index), np.append(sizes.astype(np.int32), np.int32(1)).take(index)
        out = _spread(np.append(ids, np.uint32(END)), begins, sizes)
        return out, np.diff(np.cumsum(sizes, dtype=np.int64)[index == index.max(initial=0)], prepend=0)

    def _mixed(self, texts: pa.Array, special: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        edges = np.flatnonzero(np.diff(special)) + 1
        parts = []
        for a, z in zip([0, *edges.tolist()], [*edges.tolist(), len(texts)]):
            part = texts.slice(a, z - a)
            parts.append(_joined([np.append(ids, np.uint32(END)) for ids in self.whole(part.to_pylist())]) if special[a] else self.encode(part))
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])


def _bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of an Arrow array with 64-bit offsets, and its offsets from 0."""
    _, ends, data = texts.buffers()
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    ends = np.frombuffer(ends, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, ends - ends[0]


def _spread(ids: np.ndarray, begins: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The ids of places that begin at `begins`, one place after the other."""
    ends = np.cumsum(sizes, dtype=np.int64)
    total = int(ends[-1]) if len(ends) else 0
    kind = np.int32 if max(total, len(ids)) < 1 << 31 else np.int64
    at = np.repeat((begins - (ends - sizes)).astype(kind), sizes)
    at += np.arange(total, dtype=kind)
    return ids.take(at)


def _joined(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate([np.zeros(0, np.uint32), *parts]), np.fromiter(map(len, parts), np.int64, len(parts))


def _cut(data: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, pa.Array]:
    """Where pieces begin in the bytes of texts that end at `ends`, and the pieces."""
    space = data - np.uint8(9) < 5
    space |= data == 32
    marks = data == 33
    for mark in b",.:;?":
        marks |= data == mark
    # before white space, and between a letter and a mark
    letter = (data | np.uint8(32)) - np.uint8(97) < 26
    cut = space[1:] > space[:-1]
    cut |= marks[1:] & letter[:-1]
    at = np.flatnonzero(cut) + 1
    far = at[data[at - 1] >= 128]  # Unicode's other white space may belong with what follows
    for char in OTHER_SPACE:
        code = np.frombuffer(char.encode(), np.uint8)
        same = far >= len(code)
        for k, byte in enumerate(code[::-1]):
            same &= data[far - np.minimum(far, k + 1)] == byte
        far, hit = far[~same], far[same]
        at = np.setdiff1d(at, hit, assume_unique=True) if len(hit) else at
    first = np.zeros(len(data) + 1, bool)
    first[at] = True
    first[ends[:-1]] = True
    starts = np.flatnonzero(first[:-1])
    offsets = np.append(starts, len(data)) if len(starts) else np.zeros(1, np.int64)
    return starts, pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(data)])


def _runs(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """Rows of some RUN bytes, or one longer row."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy().astype(np.int64)
    number = (np.cumsum(sizes) - sizes) // RUN
    cuts = [0, *(np.flatnonzero(np.diff(number)) + 1).tolist(), len(texts)]
    return zip(cuts, cuts[1:])


_kept: dict[str, Pieces] = {}


def pieces_of(path: str) -> Pieces:
    """The pieces of one vocabulary, kept from task to task of a Python worker."""
    if path not in _kept:
        _kept.clear()
        _kept[path] = Pieces(path)
    return _kept[path]


FRAMES = "part int, frame int, n_ids long, ids binary, doc_ids array<long>, lengths array<long>"
NAMES = ["part", "frame", "n_ids", "ids", "doc_ids", "lengths"]


def write_tokens(docs: DataFrame, tokenizer: str, path: str, frame_ids: int = 1 << 23) -> None:
    """Encode documents in ascending doc_id order into the frame table at `path`. `tokenizer` is a file's path."""

    def apply(batches):
        import os

        from pyspark import TaskContext

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        part, frame, pieces = TaskContext.get().partitionId(), 0, pieces_of(tokenizer)
        held: list[tuple[pa.Array, np.ndarray, np.ndarray]] = []

        def sealed():
            ids = np.concatenate([h[1] for h in held])
            docs, sizes = pa.concat_arrays([h[0] for h in held]), pa.array(np.concatenate([h[2] for h in held]))
            lists = [pa.ListArray.from_arrays(pa.array([0, len(a)], pa.int32()), a) for a in (docs, sizes)]
            row = [pa.array([part], pa.int32()), pa.array([frame], pa.int32()), pa.array([len(ids)]), pa.array([encode_ids(ids, pieces.vocabulary)], pa.binary()), *lists]
            return pa.RecordBatch.from_arrays(row, NAMES)

        for batch in batches:
            doc_ids, texts = batch.column(0), batch.column(1)
            for a, z in _runs(texts):
                ids, sizes = pieces.encode(texts.slice(a, z - a))
                cuts = np.cumsum(sizes)
                begin = start = 0
                # a frame ends with the document that fills it
                while start < z - a:
                    before = sum(len(h[1]) for h in held)
                    stop = min(int(np.searchsorted(cuts, begin + frame_ids - before)) + 1, z - a)
                    held.append((doc_ids.slice(a + start, stop - start), ids[begin : cuts[stop - 1]], sizes[start:stop]))
                    begin, start = int(cuts[stop - 1]), stop
                    if sum(len(h[1]) for h in held) >= frame_ids:
                        yield sealed()
                        frame, held = frame + 1, []
        if held:
            yield sealed()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    rows.mapInArrow(apply, FRAMES).write.option("compression", "none").parquet(path)


def read_tokens(spark, path: str, whole: bool = True) -> DataFrame:
    """part, frame, n, doc_id, n_tokens, ids_crc32 and (if whole) ids of every document, decoded from the frames."""
    kind = "part int, frame int, n int, doc_id long, n_tokens long, ids_crc32 long" + (", ids array<long>" if whole else "")

    def apply(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids = decode_ids(row["ids"]).astype("<u4", copy=False)
                ends = np.cumsum(np.array(row["lengths"], np.int64))
                if len(ids) != ends[-1]:
                    raise ValueError("a frame holds other ids than its documents")
                data = memoryview(ids).cast("B")
                starts = ends - row["lengths"]
                n = len(ends)
                crc = [zlib.crc32(data[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist())]
                arrays = [pa.array([row["part"]] * n, pa.int32()), pa.array([row["frame"]] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array(row["doc_ids"], pa.int64()), pa.array(row["lengths"], pa.int64()), pa.array(crc, pa.int64())]
                names = ["part", "frame", "n", "doc_id", "n_tokens", "ids_crc32"]
                if whole:
                    arrays.append(pa.ListArray.from_arrays(pa.array(np.concatenate([starts[:1], ends]), pa.int32()), pa.array(ids.astype(np.int64))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(arrays, names)

    frames = spark.read.schema(FRAMES).parquet(path)
    return frames.select("part", "frame", "ids", "doc_ids", "lengths").mapInArrow(apply, kind)


def token_digest(docs: DataFrame, tokenizer: str, frame_ids: int = 1 << 23) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, from the written frames."""
    spark = docs.sparkSession
    path = scratch(spark, "token-frames")
    write_tokens(docs, tokenizer, path, frame_ids)
    frames = spark.read.schema(FRAMES).parquet(path).select("part", "frame", "n_ids")
    before = Window.orderBy("part", "frame").rowsBetween(Window.unboundedPreceding, -1)
    # one small row for each frame of some million ids
    offsets = frames.withColumn("before", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))
    each = read_tokens(spark, path, whole=False)
    inside = Window.partitionBy("part", "frame").orderBy("n").rowsBetween(Window.unboundedPreceding, -1)
    each = each.withColumn("at", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).join(offsets, ["part", "frame"])
    return each.select("doc_id", (F.col("before") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")
