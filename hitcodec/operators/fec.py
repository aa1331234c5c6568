"""Forward error correction of payloads: Hamming(7,4) words, or an exclusive-or parity block."""

from __future__ import annotations

import numpy as np

# The generator of the code, one row for each data bit (order d1 d2 d3 d4 -> p1 p2 d1 p3 d2 d3 d4).
GENERATOR = np.array([[1, 1, 1, 0, 0, 0, 0], [1, 0, 0, 1, 1, 0, 0], [0, 1, 0, 1, 0, 1, 0], [1, 1, 0, 1, 0, 0, 1]], np.uint8)
CHECKS = np.array([[1, 0, 1, 0, 1, 0, 1], [0, 1, 1, 0, 0, 1, 1], [0, 0, 0, 1, 1, 1, 1]], np.uint8)


def hamming_encode(data: bytes) -> bytes:
    """7 bits for each 4."""
    bits = np.unpackbits(np.frombuffer(data, np.uint8)).reshape(-1, 4)
    return np.packbits((bits @ GENERATOR) % 2).tobytes()


def hamming_decode(data: bytes, size: int) -> tuple[bytes, int]:
    """The `size` bytes protected, and how many words were repaired."""
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[: size * 14].reshape(-1, 7).copy()
    at = ((bits @ CHECKS.T) % 2) @ np.array([1, 2, 4])
    bad = np.flatnonzero(at)
    bits[bad, at[bad] - 1] ^= 1
    return np.packbits(bits[:, [2, 4, 5, 6]]).tobytes(), len(bad)


def parity_encode(blocks: list[bytes]) -> bytes:
    """The exclusive or of blocks, the short ones padded with zeros."""
    size = max(map(len, blocks), default=0)
    out = np.zeros(size, np.uint8)
    for b in blocks:
        out[: len(b)] ^= np.frombuffer(b, np.uint8)
    return out.tobytes()


def parity_repair(blocks: list[bytes | None], sizes: list[int], parity: bytes) -> list[bytes]:
    """Blocks with one that is lost made good."""
    lost = [k for k, b in enumerate(blocks) if b is None]
    if len(lost) > 1:
        raise ValueError("parity makes good one block only")
    if lost:
        have = parity_encode([b for b in blocks if b is not None] + [parity])
        blocks = [have[: sizes[k]] if b is None else b for k, b in enumerate(blocks)]
    return blocks
