"""Adaptive context-mixing range coder for token ids, many blocks side by side.

A stream of ids is cut in blocks that are coded independently, each with a model of its own from the first id on:

* order 2 and order 1 keep, for a hash of the last two ids and of the last id, the id that followed, with a confidence;
* order 0 is a distribution over all ids in buckets (one id each below SINGLE, WIDE ids above);
* the mix weighs the three by how often each was right, for each pair of confidences.

The table of orders 2 and 1 learns from every id (a context's order-2 ids stand beside its order-1 id, in one cache line);
order 0 and the weights are renewed after 64, 320, 1344, ... ids.

The mix drives a range coder: its line has the share of order 2's id, that of order 1's, and order 0's whole distribution
in what is left, so that no escape symbols are needed. An id has the first of these places that holds it; what order 0
keeps for an id that a context predicts stays unused. Each step codes one id of every block at once; the coder's integers
are below 2**53 and held as doubles, which are exact there and divide fast. A frame holds a header, a table of blocks
(ids, words, CRC-32 of ids and of payload) and the payloads, in words of 16 bits; everything is checked when it is read.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

MAGIC = b"IDRC2\0\0\0"
BLOCK = 4096
LANES = 2048
SINGLE, WIDE_BITS = 512, 8
WIDE = 1 << WIDE_BITS
FIRST, GROWTH, GAIN = 64, 4, 8
TABLE_BITS = 9
# bits of the mix's weights and of order 0's distribution over buckets; a bucket's ids share it evenly
MIX, PART = 12, 12
TAIL = PART + WIDE_BITS
SCALE = MIX + TAIL
MOST = np.uint32((1 << TAIL) - 1)
# what a prediction of order 2 or 1 is trusted at first, by its confidence, and for how many ids that counts
TRUST, WEIGHT = np.array([0.1, 0.4, 0.6, 0.8]), 4
# the coder's state has 52 bits, of which the upper 16 leave as a word
LOW_RANGE, TOP, TURN = 2.0**36, 2.0**52, 2.0**16
K1, K2 = np.uint32(2654435761), np.uint32(2246822519)
CHUNK = 32  # steps whose independent parts are taken together


class _Model:
    """The models of all lanes; `ids` is the size of the vocabulary."""

    def __init__(self, lanes: int, ids: int):
        self.n = n = SINGLE + max(0, -(-(ids - SINGLE) // WIDE))
        if 2 * n > 1 << PART:
            raise ValueError("the vocabulary is too large")
        bucket, lane = np.arange(n), np.arange(lanes)
        self.first = np.where(bucket < SINGLE, bucket, (bucket << WIDE_BITS) - (SINGLE << WIDE_BITS) + SINGLE).astype(np.int32)
        self.span = np.where(bucket < SINGLE, WIDE, 1).astype(np.uint32)  # an id's part of its bucket
        self.at_bucket, self.at_slot, self.at_mix = lane * n, lane << PART, (lane << 4).astype(np.int32)
        self.at_table = lane << TABLE_BITS + 2
        self.after = np.zeros(lanes << TABLE_BITS + 2, np.int32)
        self.count, self.seen = np.zeros(lanes * n, np.int32), 0
        mix = np.arange(16)  # confidence of order 1, of order 2
        two = TRUST[mix & 3]
        one = (1 - two) * TRUST[mix >> 2]
        self.right = np.tile(WEIGHT * np.stack([1 - one - two, one, two], 1), (lanes, 1))
        self.share_ids()
        self.share_mix()

    def bucket(self, x: np.ndarray) -> np.ndarray:
        return np.minimum(x, (x >> WIDE_BITS) + (SINGLE - (SINGLE >> WIDE_BITS)))

    def renew(self, ids: np.ndarray, log: np.ndarray) -> None:
        """Learn from some more ids (steps x lanes) and from which order was right in which context of the mix."""
        place = self.bucket(np.ascontiguousarray(ids.T)) + self.at_bucket[:, None]  # lane by lane, near in memory
        self.count += np.bincount(place.ravel(), minlength=len(self.count)).astype(np.int32)
        self.seen += len(ids)
        self.right += np.bincount(log.ravel(), minlength=self.right.size).reshape(-1, 3)
        self.share_ids()
        self.share_mix()

    def share_ids(self) -> None:
        """Begin of each bucket on order 0's line (the upper 12 bits of `share`), and size of each of its ids on the WIDE times longer one."""
        n = self.n
        size = self.count * GAIN
        size += 1
        size *= (1 << PART) - n >> 1  # halved against overflow
        size //= n + GAIN * self.seen + 1 >> 1
        size += 1
        self.size = size
        size = size.reshape(-1, n)
        begin = np.cumsum(size, axis=1, dtype=np.int32)
        over = (1 << PART) - begin[:, -1:]
        begin += over
        size[:, :1] += over
        begin -= size
        share = begin.astype(np.uint32)
        share <<= np.uint32(TAIL)
        share |= size.astype(np.uint32) * self.span
        self.share = share.ravel()

    def share_mix(self) -> None:
        """Weight of order 2, and of orders 2 and 1, in each context of the mix."""
        most = (1 << MIX) * 63 // 64
        part = np.floor(self.right * (most / self.right.sum(axis=1, keepdims=True))) + 1
        self.part = (part[:, 2] * 65536 + part[:, 2] + part[:, 1]).astype(np.int32)

    def slots(self) -> np.ndarray:
        """The bucket of each of a lane's 2**PART places."""
        each = np.tile(np.arange(self.n, dtype=np.uint16), len(self.at_slot))
        return np.repeat(each, self.size)

    def weights(self, entry: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Context of the mix, ends of order 2's and order 1's share, by the entries (order 1, order 2) of the tables."""
        one, two = entry[..., 0, :], entry[..., 1, :]
        mix = one & 3
        mix <<= 2
        mix |= two & 3
        mix += self.at_mix
        part = self.part.take(mix)
        return mix, (part >> 16) * 2.0**TAIL, (part & 0xFFFF) * 2.0**TAIL

    def places(self, x: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Places in the table after ids x (... x lanes) that follow the ids `last`: order 2 has three beside each of order 1."""
        place = np.empty((*x.shape[:-1], 2, x.shape[-1]), np.int64)
        one, two = place[..., 0, :], place[..., 1, :]
        code = x.view(np.uint32) * K1
        code >>= np.uint32(32 - TABLE_BITS)
        code <<= np.uint32(2)
        np.add(self.at_table, code, out=one)
        code = last.view(np.uint32) * K2
        code >>= np.uint32(16)
        code *= np.uint32(3)
        code >>= np.uint32(16)
        code += np.uint32(1)
        np.add(one, code, out=two)
        return place

    def learn(self, place: np.ndarray, entry: np.ndarray, fresh: np.ndarray) -> np.ndarray:
        """Which of the two were right: those are surer now, the others hold the new id (`fresh`: four times the id)."""
        entry = entry ^ fresh  # the confidence where right, more where wrong
        hit = entry.view(np.uint32) < 4
        entry += 1
        np.minimum(entry, 3, out=entry)
        entry *= hit
        entry += fresh
        self.after[place.reshape(-1)] = entry.reshape(-1)
        return hit


def _segments(steps: int) -> list[tuple[int, int]]:
    """Where the models are renewed."""
    cuts, size = [0], FIRST
    while cuts[-1] + size < steps:
        cuts.append(cuts[-1] + size)
        size *= GROWTH
    return list(zip(cuts, [*cuts[1:], steps]))


def _encode_lanes(columns: np.ndarray, ids: int) -> list[bytes]:
    """Payloads of the lanes; `columns` is steps x lanes (int32)."""
    steps, lanes = columns.shape
    model = _Model(lanes, ids)
    low, width = np.zeros(lanes), np.full(lanes, TOP)
    room = steps // 2 + 3 * CHUNK + 8  # grown where that is too little
    out = np.zeros((lanes, room), np.int32)
    flat, at, begins = out.ravel(), np.arange(lanes) * room, np.arange(lanes) * room
    before = np.concatenate([np.zeros((2, lanes), np.int32), columns])
    for start, stop in _segments(steps):
        if start:
            model.renew(columns[begun:start], log)
        begun, log = start, np.empty((stop - start, lanes), np.int32)
        for k0 in range(start, stop, CHUNK):
            x = columns[k0 : min(k0 + CHUNK, stop)]
            place = model.places(before[k0 + 1 : k0 + 1 + len(x)], before[k0 : k0 + len(x)])
            entry, fresh, hit = np.empty(place.shape, np.int32), x << 2, np.empty(place.shape, bool)
            for k in range(len(x)):
                model.after.take(place[k], out=entry[k], mode="clip")
                hit[k] = model.learn(place[k], entry[k], fresh[k])
            mix, two, both = model.weights(entry)
            by2 = hit[:, 1]
            by1 = hit[:, 0] > by2
            log[k0 - start : k0 - start + len(x)] = mix * 3 + by1 + by2 * np.int8(2)
            bucket = model.bucket(x)
            share = model.share.take(model.at_bucket + bucket)
            size = (share & MOST).astype(float)
            begin = size * (x - model.first.take(bucket))
            begin += (share >> np.uint32(TAIL)).astype(float) * WIDE
            rest = 2.0**MIX - both * 2.0**-TAIL
            begin, size = both + rest * begin, rest * size
            known = np.flatnonzero(by1 | by2)
            first, split = by2.take(known), two.take(known)
            begin.ravel()[known] = np.where(first, 0.0, split)
            size.ravel()[known] = np.where(first, split, both.take(known) - split)
            for k in range(len(x)):
                width *= 2.0**-SCALE
                np.floor(width, out=width)
                low += width * begin[k]
                width *= size[k]
                small = width < LOW_RANGE
                word = low * 2.0**-36
                np.floor(word, out=word)
                flat[at] = word.astype(np.int32)  # may hold a carry above 16 bits; written over unless it leaves
                word *= small
                word *= LOW_RANGE
                low -= word
                turn = small * (TURN - 1.0)
                turn += 1.0
                low *= turn
                width *= turn
                at += small
                few = np.flatnonzero(width < LOW_RANGE)
                while len(few):
                    word = np.floor(low[few] * 2.0**-36)
                    flat[at[few]] = word.astype(np.int32)
                    low[few] = (low[few] - word * LOW_RANGE) * TURN
                    width[few] *= TURN
                    at[few] += 1
                    few = few[width[few] < LOW_RANGE]
            if int((at - begins).max()) + 3 * CHUNK + 4 > room:
                used, wider = at - begins, room // 2 + 3 * CHUNK
                out = np.concatenate([out, np.zeros((lanes, wider), np.int32)], axis=1)
                room += wider
                flat, begins = out.ravel(), np.arange(lanes) * room
                at = begins + used
    for _ in range(4):
        word = np.floor(low * 2.0**-36)
        flat[at] = word.astype(np.int32)
        at += 1
        low = (low - word * LOW_RANGE) * TURN
    used = at - begins
    out = out[:, : used.max()]
    out[np.arange(out.shape[1]) >= used[:, None]] = 0
    while (out > 0xFFFF).any():
        carry = out >> 16
        out &= 0xFFFF
        out[:, :-1] += carry[:, 1:]
    words = out.astype("<u2")
    return [words[k, : used[k]].tobytes() for k in range(lanes)]


def _decode_lanes(payloads: list[bytes], steps: int, ids: int) -> np.ndarray:
    lanes = len(payloads)
    model = _Model(lanes, ids)
    longest = max(len(p) for p in payloads) // 2 + 8
    words = np.zeros((lanes, longest), np.uint16)
    for k, p in enumerate(payloads):
        words[k, : len(p) // 2] = np.frombuffer(p, "<u2")
    code = words[:, 0] * 2.0**36 + words[:, 1] * 2.0**20 + words[:, 2] * 2.0**4 + (words[:, 3] >> 12)
    # 52 bits are no whole number of words: what comes in later starts four bits into a word
    coming = words << 4
    coming[:, :-1] |= words[:, 1:] >> 12
    coming = coming.ravel()
    at = np.arange(lanes) * longest + 3
    width = np.full(lanes, TOP)
    out = np.zeros((steps, lanes), np.int32)
    x = last = np.zeros(lanes, np.int32)
    for start, stop in _segments(steps):
        if start:
            model.renew(out[begun:start], log)
        begun, log, slots = start, np.empty((stop - start, lanes), np.int32), model.slots()
        for step in range(start, stop):
            place = model.places(x, last)
            entry = model.after.take(place)
            mix, two, both = model.weights(entry)
            rest = both * -(2.0**-TAIL)
            rest += 2.0**MIX
            unit = width * 2.0**-SCALE
            np.floor(unit, out=unit)
            v = code / unit
            np.floor(v, out=v)
            # order 0: place on its line, bucket, id in the bucket; of no account where v lies below
            spot = v - both
            spot /= rest
            np.floor(spot, out=spot)
            place0 = (spot * 2.0**-WIDE_BITS).astype(np.int64)
            place0 += model.at_slot
            bucket = slots.take(place0, mode="clip")
            np.add(model.at_bucket, bucket, out=place0)
            share = model.share.take(place0)
            size = (share & MOST).astype(float)
            share >>= np.uint32(TAIL)
            begin = share.astype(float)
            begin *= WIDE
            inside = spot
            inside -= begin
            inside /= size
            np.floor(inside, out=inside)
            begin += size * inside
            begin *= rest
            begin += both
            size *= rest
            last, x = x, model.first.take(bucket) + inside.astype(np.int32)
            guess = entry >> 2
            known = np.flatnonzero(v < both)
            if len(known):
                split = two[known]
                by2 = v[known] < split
                begin[known] = np.where(by2, 0.0, split)
                size[known] = np.where(by2, split, both[known] - split)
                x[known] = np.where(by2, guess[1, known], guess[0, known])
            out[step] = x
            code -= unit * begin
            width = unit * size
            small = width < LOW_RANGE
            turn = small * (TURN - 1.0)
            turn += 1.0
            code *= turn
            code += coming.take(at, mode="clip") * small
            width *= turn
            at += small
            few = np.flatnonzero(width < LOW_RANGE)
            while len(few):
                code[few] = code[few] * TURN + coming.take(at[few], mode="clip")
                width[few] *= TURN
                at[few] += 1
                few = few[width[few] < LOW_RANGE]
            hit = model.learn(place, entry, x << 2)
            by2 = hit[1]
            mix *= 3
            mix += hit[0] > by2
            mix += by2
            mix += by2
            log[step - start] = mix
    return out


def _groups(n: int) -> list[tuple[int, int]]:
    """Blocks that go side by side: even parts of at most LANES."""
    cuts = np.linspace(0, n, -(-n // LANES) + 1).astype(int).tolist()
    return list(zip(cuts, cuts[1:]))


def encode_ids(ids: np.ndarray, vocabulary: int, block: int = BLOCK) -> bytes:
    """A frame of one id stream."""
    ids = np.ascontiguousarray(ids, np.uint32)
    if len(ids) and int(ids.max()) >= vocabulary:
        raise ValueError("an id is beyond the vocabulary")
    block = max(1, min(block, len(ids)))
    n = -(-len(ids) // block)
    padded = np.zeros(n * block, np.int32)
    padded[: len(ids)] = ids
    padded = padded.reshape(n, block)
    payloads: list[bytes] = []
    for a, z in _groups(n):
        payloads += _encode_lanes(np.ascontiguousarray(padded[a:z].T), vocabulary)
    parts = [MAGIC, struct.pack("<QIII", len(ids), vocabulary, block, n)]
    for k, p in enumerate(payloads):
        part = ids[k * block : (k + 1) * block]
        parts.append(struct.pack("<IIII", len(part), len(p) // 2, zlib.crc32(part.astype("<u4").tobytes()), zlib.crc32(p)))
    parts.append(struct.pack("<I", zlib.crc32(b"".join(parts))))
    return b"".join([*parts, *payloads])


def decode_ids(frame: bytes) -> np.ndarray:
    """The ids of a frame; ValueError if a check fails."""
    if frame[:8] != MAGIC:
        raise ValueError("not a frame of token ids")
    total, vocabulary, block, n = struct.unpack_from("<QIII", frame, 8)
    at = 28
    table = [struct.unpack_from("<IIII", frame, at + 16 * k) for k in range(n)]
    at += 16 * n
    if zlib.crc32(frame[:at]) != struct.unpack_from("<I", frame, at)[0]:
        raise ValueError("damaged header")
    at += 4
    payloads = []
    for _, words, _, check in table:
        payloads.append(frame[at : at + 2 * words])
        if zlib.crc32(payloads[-1]) != check:
            raise ValueError("damaged block")
        at += 2 * words
    out = [np.zeros(0, np.uint32)]
    for a, z in _groups(n):
        got = _decode_lanes(payloads[a:z], block, vocabulary)
        out.append(np.ascontiguousarray(got.T).ravel().astype(np.uint32))
    ids = np.concatenate(out)[:total]
    for k, (size, _, check, _) in enumerate(table):
        if zlib.crc32(ids[k * block : k * block + size].astype("<u4").tobytes()) != check:
            raise ValueError("a block decodes to other ids")
    return ids
