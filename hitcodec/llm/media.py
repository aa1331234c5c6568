"""Media columns: Netpbm and BMP pictures to numpy arrays, area-resized tiles as NPY bytes, and difference hashes.

`decode` reads Netpbm P2, P3, P5, P6 (8 bits) and uncompressed BMP of 8, 24 and 32 bits. `area_resize` averages the
source area under each target pixel, with exact fractional edges, from an integral image. A tile is the resized grey
picture in NPY format; the difference hash compares neighbours of a 9 x 8 one. `store_texts` keeps any bytes losslessly as
a grey picture 64 samples wide; the pictures, and then their tiles, are written to tables in the shared folder and read
back.

Defined results: null text is empty and gives one row of zeros; a null doc_id is kept as it is; equal texts give equal
values; a very long text is one tall picture, held by one task with its integral image (8 bytes a sample); an empty table
gives an empty result; a picture that can't be read raises ValueError, in `media_features` it gives nulls; repeated rows
each get a row; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import io
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hitcodec.session import materialise

WIDTH = 64


def _tokens(data: bytes, n: int, at: int = 2) -> tuple[list[int], int]:
    """n header numbers of a Netpbm file, comments skipped, and where they end."""
    found = []
    while len(found) < n:
        while at < len(data) and data[at : at + 1].isspace():
            at += 1
        if data[at : at + 1] == b"#":
            at = data.index(b"\n", at)
            continue
        end = at
        while end < len(data) and data[end : end + 1].isdigit():
            end += 1
        if end == at:
            raise ValueError("not a Netpbm header")
        found.append(int(data[at:end]))
        at = end
    return found, at


def decode_netpbm(data: bytes) -> np.ndarray:
    """Height x width, or x 3 for colour, of uint8."""
    kind = data[:2]
    if kind not in (b"P2", b"P3", b"P5", b"P6"):
        raise ValueError("not a Netpbm file of this kind")
    (w, h, top), at = _tokens(data, 3)
    if not 0 < top < 256:
        raise ValueError("only 8-bit samples")
    depth = 3 if kind in (b"P3", b"P6") else 1
    if kind in (b"P5", b"P6"):
        pixels = np.frombuffer(data, np.uint8, w * h * depth, at + 1)
    else:
        pixels = np.array(data[at:].split()[: w * h * depth], dtype=np.uint8)
        if len(pixels) < w * h * depth:
            raise ValueError("short Netpbm file")
    return pixels.reshape(h, w, 3) if depth == 3 else pixels.reshape(h, w)


def decode_bmp(data: bytes) -> np.ndarray:
    """Height x width (grey palettes as stored) or x 3 (red, green, blue) of uint8."""
    if data[:2] != b"BM" or len(data) < 54:
        raise ValueError("not a BMP file")
    word = lambda at, n=4, signed=False: int.from_bytes(data[at : at + n], "little", signed=signed)
    start, w, h, bits, packed = word(10), word(18, signed=True), word(22, signed=True), word(28, 2), word(30)
    if packed not in (0, 3) or bits not in (8, 24, 32):
        raise ValueError("only uncompressed BMP of 8, 24 or 32 bits")
    stride = (w * bits + 31) // 32 * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(h), start).reshape(abs(h), stride)[:, : w * bits // 8]
    if h > 0:
        rows = rows[::-1]
    if bits == 8:
        palette = np.frombuffer(data, np.uint8, 4 * (word(46) or 256), 14 + word(14)).reshape(-1, 4)[:, 2::-1]
        colours = palette[rows]
        return colours[..., 0] if (palette == palette[:, :1]).all() else colours
    return rows.reshape(abs(h), w, bits // 8)[..., 2::-1]


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def encode_pgm(pixels: np.ndarray) -> bytes:
    return b"P5\n%d %d\n255\n" % (pixels.shape[1], pixels.shape[0]) + pixels.tobytes()


def encode_bmp(pixels: np.ndarray) -> bytes:
    """A grey picture as 8-bit BMP with a grey palette."""
    h, w = pixels.shape
    stride = (w + 3) // 4 * 4
    rows = np.zeros((h, stride), np.uint8)
    rows[:, :w] = pixels[::-1]
    number = lambda x, n=4: int(x).to_bytes(n, "little")
    palette = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 4, axis=1)
    palette[:, 3] = 0
    head = b"BM" + number(1078 + stride * h) + number(0) + number(1078)
    info = number(40) + number(w) + number(h) + number(1, 2) + number(8, 2) + number(0) + number(stride * h) + number(2835) + number(2835) + number(256) + number(0)
    return head + info + palette.tobytes() + rows.tobytes()


def grey(pixels: np.ndarray) -> np.ndarray:
    """Luma of a colour picture, with integer weights."""
    if pixels.ndim == 2:
        return pixels
    return ((pixels.astype(np.uint32) * np.array([299, 587, 114], np.uint32)).sum(-1) // 1000).astype(np.uint8)


def _edges(n: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    at = np.arange(m + 1) * n / m
    low = np.minimum(np.floor(at).astype(np.int64), n - 1)
    return low, at - low


def area_resize(pixels: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the area under each target pixel, as float64, by an integral image."""
    h, w = pixels.shape
    total = np.zeros((h + 1, w + 1), np.float64)
    np.cumsum(np.cumsum(pixels, axis=0, dtype=np.int64), axis=1, out=total[1:, 1:])
    (y, fy), (x, fx) = _edges(h, height), _edges(w, width)
    rows = total[y] * (1 - fy)[:, None] + total[y + 1] * fy[:, None]
    both = rows[:, x] * (1 - fx) + rows[:, x + 1] * fx
    return np.diff(np.diff(both, axis=0), axis=1) / ((h / height) * (w / width))


def difference_hash(pixels: np.ndarray) -> str:
    """64 bits, hexadecimal: is each pixel of the 9 x 8 picture brighter than its left neighbour."""
    small = area_resize(grey(pixels), 8, 9)
    return np.packbits(small[:, 1:] > small[:, :-1] + 1e-9).tobytes().hex()


def tile(pixels: np.ndarray, side: int = 16) -> bytes:
    """The resized grey picture in NPY format."""
    out = io.BytesIO()
    np.save(out, np.rint(area_resize(grey(pixels), side, side)).astype(np.uint8), allow_pickle=False)
    return out.getvalue()


def media_features(media: DataFrame, column: str = "media", side: int = 16) -> DataFrame:
    """The rows with height, width, dhash and tile (NPY bytes) of a picture column; nulls where it can't be read."""
    from pyspark.sql import types as T

    schema = T.StructType([*media.schema.fields, T.StructField("height", T.IntegerType()), T.StructField("width", T.IntegerType()), T.StructField("dhash", T.StringType()), T.StructField("tile", T.BinaryType())])
    names = schema.fieldNames()
    if len(set(names)) < len(names):
        raise ValueError("rename the columns height, width, dhash and tile first")
    at = media.columns.index(column)

    def one(data):
        try:
            pixels = decode(data)
            return (*pixels.shape[:2], difference_hash(pixels), tile(pixels, side))
        except (ValueError, TypeError):
            return None, None, None, None

    def apply(batches):
        for batch in batches:
            made = [one(x) for x in batch.column(at).to_pylist()]
            new = [pa.array([m[i] for m in made], t) for i, t in enumerate((pa.int32(), pa.int32(), pa.string(), pa.binary()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *new], names)

    return media.mapInArrow(apply, schema)


def text_payload(text: str | None) -> tuple[int, bytes]:
    """UTF-8 length, and the bytes with zeros up to a positive multiple of the width."""
    data = (text or "").encode()
    return len(data), data + bytes(-len(data) % WIDTH or (0 if data else WIDTH))


def store_texts(docs: DataFrame, form: str = "pgm") -> DataFrame:
    """doc_id, n_bytes, media: every text as a picture, written to the shared folder and read again."""
    encode = {"pgm": encode_pgm, "bmp": encode_bmp}[form]

    def apply(batches):
        for batch in batches:
            made = [text_payload(t) for t in batch.column(1).to_pylist()]
            media = [encode(np.frombuffer(p, np.uint8).reshape(-1, WIDTH)) for _, p in made]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([m[0] for m in made], pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    rows = docs.selectExpr("cast(doc_id as long) as doc_id", "text").mapInArrow(apply, "doc_id long, n_bytes long, media binary")
    return materialise(rows, "media")


def store_tiles(stored: DataFrame, side: int = 16) -> DataFrame:
    """What the stored pictures hold, decoded, with the difference hash and the tile in NPY format: written to the shared
    folder and read again."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "tile"]

    def one(data: bytes):
        pixels = decode(data)
        payload = pixels.tobytes()
        return len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-WIDTH:]), len(data), hashlib.sha256(data).hexdigest(), difference_hash(pixels), tile(pixels, side)

    kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary())

    def apply(batches):
        for batch in batches:
            made = [one(x) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array([m[i] for m in made], k) for i, k in enumerate(kinds))], names)

    made = stored.select("doc_id", "n_bytes", "media").mapInArrow(apply, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tile binary")
    return materialise(made, "media-tiles")


def media_digest(stored: DataFrame, side: int = 16) -> DataFrame:
    """Digests of payload, picture and NPY tile, each as read back, and the difference hash."""
    return store_tiles(stored, side).withColumn("tile_sha256", F.sha2("tile", 256)).drop("tile")
