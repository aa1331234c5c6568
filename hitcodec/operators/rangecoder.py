"""Range coder with a static model: the accurate baseline that multiplies. Frames step together, as in tans."""

from __future__ import annotations

import numpy as np

TOTAL_BITS = 16
U = np.uint64
LOW = U(1 << 32)
PART = U((1 << 32) - 1)


def model(counts) -> np.ndarray:
    """Cumulative frequencies summing to 2**16, every symbol at least one."""
    n = np.asarray(counts, np.float64)
    total = 1 << TOTAL_BITS
    f = np.maximum(1, np.floor(n / n.sum() * total)).astype(np.int64)
    f[int(np.argmax(f))] += total - f.sum()
    if f.min() < 1:
        raise ValueError("too many symbols")
    return np.concatenate([[0], np.cumsum(f)])


def range_encode(frames: list[np.ndarray], cum: np.ndarray) -> list[bytes]:
    """Payload of each frame, in 16-bit words."""
    n, out = len(frames), []
    lengths = np.array([len(f) for f in frames], np.int64)
    longest = int(lengths.max()) if n else 0
    grid = np.zeros((n, longest), np.int64)
    for k, f in enumerate(frames):
        grid[k, : len(f)] = f
    low, width = np.zeros(n, U), np.full(n, 1 << 48, U)
    words, used = np.zeros((n, longest + 8), np.int64), np.zeros(n, np.int64)
    begin, size = cum[:-1].astype(U), np.diff(cum).astype(U)
    for step in range(longest):
        live = np.flatnonzero(lengths > step)
        s = grid[live, step]
        unit = width[live] >> U(TOTAL_BITS)
        low[live] += unit * begin[s]
        width[live] = unit * size[s]
        small = live[width[live] < LOW]
        words[small, used[small]] = (low[small] >> U(32)).astype(np.int64)
        used[small] += 1
        low[small] = (low[small] & PART) << U(16)
        width[small] <<= U(16)
    for _ in range(3):
        words[np.arange(n), used] = (low >> U(32)).astype(np.int64)
        used += 1
        low = (low & PART) << U(16)
    while (words > 0xFFFF).any():
        carry = words >> 16
        words &= 0xFFFF
        words[:, :-1] += carry[:, 1:]
    for k in range(n):
        out.append(words[k, : used[k]].astype("<u2").tobytes())
    return out


def range_decode(payloads: list[bytes], lengths: list[int], cum: np.ndarray) -> list[np.ndarray]:
    """The symbols of frames of known lengths."""
    n, sizes = len(payloads), np.array(lengths, np.int64)
    longest = int(sizes.max()) if n else 0
    width_words = max((len(p) // 2 for p in payloads), default=0) + 1
    words = np.zeros((n, width_words), U)
    for k, p in enumerate(payloads):
        words[k, : len(p) // 2] = np.frombuffer(p, "<u2")
    symbol_of = np.repeat(np.arange(len(cum) - 1), np.diff(cum))
    begin, size = cum[:-1].astype(U), np.diff(cum).astype(U)
    code = (words[:, 0] << U(32)) | (words[:, 1] << U(16)) | words[:, 2] if n else np.zeros(0, U)
    used, width = np.full(n, 3, np.int64), np.full(n, 1 << 48, U)
    grid = np.zeros((n, longest), np.int64)
    top = U((1 << TOTAL_BITS) - 1)
    for step in range(longest):
        live = np.flatnonzero(sizes > step)
        unit = width[live] >> U(TOTAL_BITS)
        s = symbol_of[np.minimum(code[live] // unit, top).astype(np.int64)]
        grid[live, step] = s
        code[live] -= unit * begin[s]
        width[live] = unit * size[s]
        small = live[width[live] < LOW]
        code[small] = (code[small] << U(16)) | words[small, used[small]]
        used[small] += 1
        width[small] <<= U(16)
    return [grid[k, : sizes[k]] for k in range(n)]
