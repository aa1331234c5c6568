"""Huffman codes: lengths by merging the two least, depth limits by packages, canonical words, checks, escape symbols.

Fitting works on counts of an alphabet (some hundred symbols) in the driver or in a task of a group; streams are encoded
in Arrow batches with table look-ups.
"""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def huffman_lengths(counts: dict[int, int], max_len: int | None = None) -> dict[int, int]:
    """Optimal word lengths, at most max_len; a lone symbol gets one bit."""
    used = {s: n for s, n in counts.items() if n > 0}
    if len(used) < 2:
        return dict.fromkeys(used, 1)
    if max_len is not None:
        return _packages(used, max_len)
    heap = [(n, s, (s,)) for s, n in used.items()]
    heapq.heapify(heap)
    depth = dict.fromkeys(used, 0)
    while len(heap) > 1:
        n1, k1, s1 = heapq.heappop(heap)
        n2, k2, s2 = heapq.heappop(heap)
        for s in (*s1, *s2):
            depth[s] += 1
        heapq.heappush(heap, (n1 + n2, min(k1, k2), s1 + s2))
    return depth


def _packages(counts: dict[int, int], max_len: int) -> dict[int, int]:
    if len(counts) > 1 << max_len:
        raise ValueError("too many symbols for words of this length")
    single = sorted((n, (s,)) for s, n in counts.items())
    level = single
    for _ in range(max_len - 1):
        paired = [(a[0] + b[0], a[1] + b[1]) for a, b in zip(level[::2], level[1::2])]
        level = sorted(single + paired, key=lambda x: x[0])
    depth = dict.fromkeys(counts, 0)
    for _, symbols in level[: 2 * len(counts) - 2]:
        for s in symbols:
            depth[s] += 1
    return depth


def huffman_bits(counts) -> int:
    """Total bits of an optimal prefix code, without the code: the sum of all merged weights."""
    heap = [int(n) for n in counts if n > 0]
    if len(heap) == 1:
        return heap[0]
    heapq.heapify(heap)
    total = 0
    while len(heap) > 1:
        n = heapq.heappop(heap) + heapq.heappop(heap)
        total += n
        heapq.heappush(heap, n)
    return total


def canonical_codes(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """symbol: (length, word); words count up by length, then symbol."""
    word, last, found = 0, 0, {}
    for s, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        word <<= n - last
        found[s] = (n, word)
        word, last = word + 1, n
    return found


def kraft_sum(lengths) -> float:
    return sum(2.0**-n for n in lengths)


def codebook(spark, codes: dict[int, tuple[int, int]]) -> DataFrame:
    """sym, len, code, word."""
    rows = [(s, n, w, format(w, f"0{n}b")) for s, (n, w) in sorted(codes.items())]
    return spark.createDataFrame(rows, "sym int, len int, code long, word string")


def prefix_clashes(book: DataFrame) -> DataFrame:
    """Pairs of words of which one begins the other: none in a prefix code. Words meet by their first bits (equi-join)."""
    shortest = F.broadcast(book.agg(F.min("len").alias("least")))
    cut = lambda d: d.crossJoin(shortest).withColumn("k", F.substring("word", F.lit(1), F.col("least")))
    a = cut(book.select(F.col("sym").alias("a"), "word", "len")).select("a", F.col("word").alias("wa"), "k")
    b = cut(book.select(F.col("sym").alias("b"), "word", "len")).select("b", F.col("word").alias("wb"), "k")
    return a.join(b, "k").where("a <> b and startswith(wb, wa)").select("a", "b")


def with_escape(counts: dict[int, int], max_sym: int) -> tuple[dict[int, int], int]:
    """Counts in which all symbols above max_sym are one escape symbol, and that symbol."""
    escape = max_sym + 1
    kept = {s: n for s, n in counts.items() if s <= max_sym}
    rest = sum(n for s, n in counts.items() if s > max_sym)
    return (kept | {escape: rest} if rest else kept), escape


def encode_bits(symbols: np.ndarray, codes: dict[int, tuple[int, int]]) -> tuple[bytes, int]:
    """The words of symbols, one after the other, the most significant bit first; and the number of bits."""
    if not len(symbols):
        return b"", 0
    size = max(codes) + 1
    length, word = np.zeros(size, np.int64), np.zeros(size, np.int64)
    for s, (n, w) in codes.items():
        length[s], word[s] = n, w
    n, w = length[symbols], word[symbols]
    if (n == 0).any():
        raise ValueError("a symbol has no word")
    ends = np.cumsum(n)
    owner = np.repeat(np.arange(len(symbols)), n)
    place = np.arange(int(ends[-1])) - np.repeat(ends - n, n)
    bits = (w[owner] >> (n[owner] - 1 - place)) & 1
    return np.packbits(bits.astype(np.uint8)).tobytes(), int(ends[-1])


def decode_bits(data: bytes, count: int, codes: dict[int, tuple[int, int]]) -> np.ndarray:
    """The first `count` symbols of a bit string, by a table over all words of the greatest length."""
    deep = max(n for n, _ in codes.values())
    symbol, length = np.zeros(1 << deep, np.int64), np.zeros(1 << deep, np.int64)
    for s, (n, w) in codes.items():
        symbol[w << (deep - n) : (w + 1) << (deep - n)] = s
        length[w << (deep - n) : (w + 1) << (deep - n)] = n
    bits = np.unpackbits(np.frombuffer(data, np.uint8))
    bits = np.concatenate([bits, np.zeros(deep, np.uint8)]).astype(np.int64)
    window = np.zeros(len(bits) - deep + 1, np.int64)
    for k in range(deep):
        window = window << 1 | bits[k : len(bits) - deep + 1 + k]
    sizes, found, at, out = length.tolist(), symbol, 0, []
    window = window.tolist()
    for _ in range(count):
        out.append(window[at])
        at += sizes[window[at]]
    return found[np.array(out, np.int64)] if out else np.zeros(0, np.int64)
