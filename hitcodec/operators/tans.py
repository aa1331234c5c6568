"""Tabled asymmetric numeral systems: quotas, spreads, tables, exact loss, and coders that run many frames in step.

A model is a plain dict of NumPy arrays, a few kilobytes, that closures and broadcasts carry to the executors. States are
kept in [L, 2L), L = 2**R. Bits are appended with the most significant bit of each chunk first; the decoder takes chunks
from the end.
"""

from __future__ import annotations

import itertools
import math

import numpy as np


def quotas(counts, r: int) -> np.ndarray:
    """Slots of each symbol: at least one each, summing to 2**r, close to its share; by least loss of bits a correction."""
    n = np.asarray(counts, np.float64)
    size = 1 << r
    if (n <= 0).any():
        raise ValueError("every symbol needs a count")
    if len(n) > size:
        raise ValueError("more symbols than states")
    q = np.maximum(1, np.floor(n / n.sum() * size + 0.5)).astype(np.int64)
    while q.sum() > size:
        cost = np.where(q > 1, n * np.log2(q / np.maximum(q - 1, 1)), np.inf)
        q[int(np.argmin(cost))] -= 1
    while q.sum() < size:
        q[int(np.argmax(n * np.log2((q + 1) / q)))] += 1
    return q


def spread_step(r: int) -> int:
    """A stride near 5/8 of the table that visits every slot."""
    size = 1 << r
    step = (5 * size) // 8 + 3
    while math.gcd(step, size) > 1:
        step += 1
    return step


def spread(quota, r: int, kind: str = "step") -> np.ndarray:
    """Slot to symbol. step: a stride over the table; block: runs; reverse: runs in bit-reversed order; precise: each
    symbol at the centres of equal parts of the table."""
    quota = np.asarray(quota, np.int64)
    size = 1 << r
    runs = np.repeat(np.arange(len(quota)), quota)
    if kind == "block":
        return runs
    if kind == "step":
        out = np.empty(size, np.int64)
        out[np.arange(size) * spread_step(r) % size] = runs
        return out
    if kind == "reverse":
        out = np.empty(size, np.int64)
        out[[int(format(k, f"0{r}b")[::-1], 2) if r else 0 for k in range(size)]] = runs
        return out
    if kind == "precise":
        place = np.concatenate([(np.arange(q) + 0.5) * size / q for q in quota])
        return runs[np.lexsort((runs, place))]
    raise ValueError(f"no such spread: {kind}")


def spread_best(quota, r: int, p) -> tuple[np.ndarray, float]:
    """Of all slot lists of a tiny table, one of least loss."""
    best = (math.inf, None)
    size = 1 << r
    if len(quota) != 2 or size > 16:
        raise ValueError("exhaustive search is for two symbols and tiny tables")
    for some in itertools.combinations(range(size), int(quota[1])):
        slots = np.zeros(size, np.int64)
        slots[list(some)] = 1
        best = min(best, (loss(model_of(slots, r), p)["loss"], tuple(slots)))
    return np.array(best[1]), best[0]


def decoder_table(slots: np.ndarray, r: int) -> dict[str, np.ndarray]:
    """For each slot: its symbol, the bits to read, and the state they are added to, less L."""
    size, m = 1 << r, int(slots.max()) + 1
    quota = np.bincount(slots, minlength=m)
    rank = np.empty(size, np.int64)
    for s in range(m):
        at = np.flatnonzero(slots == s)
        rank[at] = np.arange(len(at))
    x = quota[slots] + rank  # the symbol's own state, in [q, 2q)
    bits = r - (np.frexp(x)[1] - 1)
    return {"sym": slots, "nbits": bits.astype(np.int64), "base": (x << bits) - size}


def encoder_table(slots: np.ndarray, r: int) -> dict[str, np.ndarray]:
    """For each symbol nb and off, and the next states; bits of a step are (state + nb) >> (r + 1)."""
    size, m = 1 << r, int(slots.max()) + 1
    quota = np.bincount(slots, minlength=m)
    k = r - (np.frexp(quota)[1] - 1)  # most bits a step of the symbol can emit
    nb = (k << (r + 1)) - (quota << k)
    off = np.concatenate([[0], np.cumsum(quota)[:-1]]) - quota
    order = np.argsort(slots, kind="stable")
    return {"nb": nb, "off": off, "next": order + size}


def model_of(slots: np.ndarray, r: int) -> dict:
    slots = np.asarray(slots, np.int64)
    return {"r": r, "slots": slots, "quota": np.bincount(slots), "dec": decoder_table(slots, r), "enc": encoder_table(slots, r)}


def fit(counts, r: int | None = None, kind: str = "step") -> dict:
    """A model of counts of symbols 0..m-1."""
    r = choose_r(len(counts)) if r is None else r
    return model_of(spread(quotas(counts, r), r, kind), r)


def choose_r(m: int, ratio: int = 8) -> int:
    """Table bits for about `ratio` states a symbol."""
    return max(1, (max(1, m * ratio) - 1).bit_length())


def join_models(models: list[dict]) -> dict:
    """Models of equal r as one whose symbols are numbered through: each step may take another's tables, on one state.

    `first` is the number of each model's first symbol; the decoder is told the model of each symbol."""
    r = models[0]["r"]
    if any(m["r"] != r for m in models):
        raise ValueError("models of different table sizes")
    sizes = [len(m["quota"]) for m in models]
    first = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.int64)
    enc = {"nb": np.concatenate([m["enc"]["nb"] for m in models]), "off": np.concatenate([m["enc"]["off"] + (k << r) for k, m in enumerate(models)]), "next": np.concatenate([m["enc"]["next"] for m in models])}
    dec = {"sym": np.concatenate([m["dec"]["sym"] + a for m, a in zip(models, first)])} | {k: np.concatenate([m["dec"][k] for m in models]) for k in ("nbits", "base")}
    return {"r": r, "quota": np.concatenate([m["quota"] for m in models]), "first": first, "enc": enc, "dec": dec}


def table_bytes(model: dict) -> int:
    """Decoder: a symbol, a bit count and a state in 4 bytes a slot. Encoder: two bytes a slot, six a symbol."""
    return (4 << model["r"]) + (2 << model["r"]) + 6 * len(model["quota"])


def stationary(model: dict, p, rounds: int = 10_000) -> np.ndarray:
    """Share of time in each state for independent symbols of probabilities p; damped, since the chain can be periodic."""
    size, enc, p = 1 << model["r"], model["enc"], np.asarray(p, np.float64)
    state = np.arange(size) + size
    step = []
    for s in range(len(p)):
        bits = (state + enc["nb"][s]) >> (model["r"] + 1)
        step.append(enc["next"][enc["off"][s] + (state >> bits)] - size)
    rho = np.full(size, 1 / size)
    for _ in range(rounds):
        new = np.zeros(size)
        for s, to in enumerate(step):
            new += np.bincount(to, rho * p[s], size)
        new = (new + rho) / 2
        done = np.abs(new - rho).max() < 1e-14
        rho = new
        if done:
            break
    return rho


def loss(model: dict, p) -> dict[str, float]:
    """rate: bits a symbol of the coder; entropy: of p; loss: their difference."""
    p = np.asarray(p, np.float64)
    p = p / p.sum()
    rho = stationary(model, p)
    state = np.arange(1 << model["r"]) + (1 << model["r"])
    rate = sum(p[s] * float(rho @ ((state + model["enc"]["nb"][s]) >> (model["r"] + 1))) for s in range(len(p)))
    h = float(-(p[p > 0] * np.log2(p[p > 0])).sum())
    return {"rate": rate, "entropy": h, "loss": rate - h}


def trace(symbols, model: dict, state: int) -> list[tuple[int, int, int, float, str, int]]:
    """Encoding step by step: step, symbol, state, its fractional bits, bits put out, next state."""
    rows = []
    for k, s in enumerate(symbols):
        bits = int(state + model["enc"]["nb"][s]) >> (model["r"] + 1)
        out = format(state & ((1 << bits) - 1), f"0{bits}b") if bits else ""
        new = int(model["enc"]["next"][model["enc"]["off"][s] + (state >> bits)])
        rows.append((k, int(s), state, math.log2(state), out, new))
        state = new
    return rows


def _by_length(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lanes by falling length, and how many lanes are live at each step."""
    order = np.argsort(-lengths, kind="stable")
    longest = int(lengths.max()) if len(lengths) else 0
    return order, np.searchsorted(-lengths[order], -np.arange(longest), "left")


def encode_frames(frames: list[np.ndarray], model: dict, start: list[int] | None = None, backward: bool = False) -> list[tuple[bytes, int, int]]:
    """(payload, bits, final state) of each frame; all frames step together. start: states in [L, 2L) that carry data.

    backward: symbols are coded from the last to the first, so that decoding gives them in order. Bits gather in 64-bit
    words of each lane and leave 32 at a time."""
    size, r, n = 1 << model["r"], model["r"], len(frames)
    nb, off, nxt = (model["enc"][k].astype(np.int32) for k in ("nb", "off", "next"))
    lengths = np.array([len(f) for f in frames], np.int64)
    order, live = _by_length(lengths)
    grid = np.zeros((n, len(live)), np.int32)
    for lane, k in enumerate(order):
        f = np.asarray(frames[k])
        grid[lane, : lengths[k]] = f[::-1] if backward else f
    grid = np.ascontiguousarray(grid.T)
    state = (np.full(n, size, np.int32) if start is None else np.asarray(start, np.int32))[order]
    held, have = np.zeros(n, np.uint64), np.zeros(n, np.int32)
    words, used = np.zeros((n, len(live) * (r + 1) // 32 + 2), np.uint32), np.zeros(n, np.int64)
    every = max(1, 32 // max(r, 1))  # steps between looks for full words
    step = 0
    for symbols, m in zip(grid, live.tolist()):
        s, x = symbols[:m], state[:m]
        bits = (x + nb[s]) >> (r + 1)
        held[:m] = (held[:m] << bits.astype(np.uint64)) | (x & ((1 << bits) - 1)).astype(np.uint64)
        have[:m] += bits
        state[:m] = nxt[off[s] + (x >> bits)]
        step += 1
        if step % every == 0:
            full = np.flatnonzero(have >= 32)
            have[full] -= 32
            words[full, used[full]] = (held[full] >> have[full].astype(np.uint64)).astype(np.uint32)
            used[full] += 1
    full = np.flatnonzero(have >= 32)
    have[full] -= 32
    words[full, used[full]] = (held[full] >> have[full].astype(np.uint64)).astype(np.uint32)
    used[full] += 1
    total = used * 32 + have
    words[np.arange(n), used] = (held << (32 - have).astype(np.uint64)).astype(np.uint32)
    data = words.astype(">u4")
    out: list = [None] * n
    for lane, k in enumerate(order.tolist()):
        out[k] = (data[lane].tobytes()[: (int(total[lane]) + 7) // 8], int(total[lane]), int(state[lane]))
    return out


def decode_frames(frames: list[tuple[bytes, int, int, int]], model: dict, backward: bool = False, which: list[np.ndarray] | None = None) -> tuple[list[np.ndarray], list[int]]:
    """Symbols and start states of frames given as (payload, bits, final state, symbols).

    which: with joined models, the model of each symbol of each frame."""
    size, r, n = 1 << model["r"], model["r"], len(frames)
    sym, nbits, base = (model["dec"][k].astype(np.int32) for k in ("sym", "nbits", "base"))
    lengths = np.array([f[3] for f in frames], np.int64)
    order, live = _by_length(lengths)
    # each lane's words behind one of zeros, so that the bits before any place lie in two neighbours
    sizes = np.array([len(frames[k][0]) // 4 + 2 for k in order], np.int64)
    first = np.concatenate([[0], np.cumsum(sizes)])
    words = np.zeros(int(first[-1]) + 1, np.uint32)
    for lane, k in enumerate(order.tolist()):
        data = frames[k][0]
        words[first[lane] + 1 : first[lane] + 1 + -(-len(data) // 4)] = np.frombuffer(data + bytes(-len(data) % 4), ">u4")
    words = words.astype(np.uint64)
    at = (first[:-1] + 1) * 32 + np.array([frames[k][1] for k in order], np.int64)
    state = np.array([frames[k][2] for k in order], np.int32)
    grid = np.zeros((len(live), n), np.int32)
    shift = None
    if which is not None:
        shift = np.zeros((n, len(live)), np.int32)
        for lane, k in enumerate(order.tolist()):
            shift[lane, : lengths[k]] = (which[k] if backward else which[k][::-1]) << r
        shift = np.ascontiguousarray(shift.T)
    for step, (row, m) in enumerate(zip(grid, live.tolist())):
        x, end = state[:m] - size, at[:m]
        if shift is not None:
            x = x + shift[step, :m]
        row[:m] = sym[x]
        nb = nbits[x]
        place = end >> 5
        both = (words[place - 1] << np.uint64(32)) | words[place]
        low = (both >> (32 - (end & 31)).astype(np.uint64)).astype(np.int64) & ((1 << nb) - 1)
        state[:m] = size + base[x] + low
        at[:m] -= nb
    grid = np.ascontiguousarray(grid.T)
    symbols: list = [None] * n
    starts = [0] * n
    for lane, k in enumerate(order.tolist()):
        got = grid[lane, : lengths[k]].astype(np.int64)
        symbols[k] = got if backward else got[::-1]
        starts[k] = int(state[lane])
    return symbols, starts
