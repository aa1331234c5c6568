"""Frames: some thousand events each, coded on their own, checksummed, written as Parquet and read back in parts.

A frame is one row; each value type has its own columns (symbols, final state, bits, payload, raw bits), so that reading
one type prunes the others, and lo_event/hi_event let a reader skip row groups. Symbols of many frames are coded side by
side in Arrow batches. Models are one for all channels, or one for each channel, class or unit: all of a value type step
on one state. Values beyond the fitted bins go to wide end bins; numbers of pulses beyond the alphabet to an escape symbol
with the excess as an Exp-Golomb word. Reference times are differences of as many bits as the frame's greatest needs.
Numbers of pulses are those of all channels of all events, or (sparse models, for many and mostly silent channels) those
of active channels, whose places go before the excesses as low bits and a bitmap of the rest (`pack_places`).
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hitcodec.operators import tans
from hitcodec.operators.bins import adaptive_bins
from hitcodec.operators.layout import value_streams
from hitcodec.session import materialise
from hitcodec.sources.views import div

NUMERIC = ("start", "width", "distance")
TYPES = ("pulses", *NUMERIC)
TAIL = 62  # low bits of the two end bins: all differences of times
PER_TYPE = "{0}_n long, {0}_state int, {0}_bits long, {0}_payload binary, {0}_raw binary"
FRAME = "frame long, lo_event long, hi_event long, n_hits long, refs binary, " + ", ".join(PER_TYPE.format(t) for t in TYPES) + ", crc long"
NAMES = [f.split()[0] for f in FRAME.split(", ")]


def fit_models(hits: DataFrame, n_channels: int, share: int = 256, max_pulses: int = 15, ratio: int = 8, scopes: list[int] | None = None, sparse: bool = False) -> dict:
    """Models of each value type, a few kilobytes in all, from histograms that the cluster counts.

    scopes: a model's number for each channel, from 0 (numbers of channels, of their classes or units); none: one model.
    sparse: frames hold nothing for silent channels, so that their size and work follow the hits."""
    many = max(scopes) + 1 if scopes else 1
    scope = F.element_at(F.lit([int(x) for x in scopes]), F.col("channel") + 1) if scopes else F.lit(0)
    values = value_streams(hits).groupBy(scope.alias("scope"), "vtype", "v").agg(F.count(F.lit(1)).alias("n"))
    values = materialise(values, "frame-models")
    width = [0] * many
    for k in scopes or range(1):
        width[k] += 1
    # silent channels are the zeros that the events leave
    events = hits.select("event").distinct().count()
    seen = [dict() for _ in range(many)]
    for x in values.where(f"vtype = 'pulses' and v <= {max_pulses}").collect():
        seen[x["scope"]][x["v"]] = x["n"]
    active = {x["scope"]: x["n"] for x in values.where("vtype = 'pulses'").groupBy("scope").agg(F.sum("n").alias("n")).collect()}
    for k, counts in enumerate(seen):
        counts[0] = 0 if sparse else events * (width[k] if scopes else n_channels) - active.get(k, 0)
    top = max(max(c) for c in seen)
    symbols = [[max(1, c.get(v, 0)) for v in range(top + 1)] + [1] for c in seen]  # the last is the escape
    r = tans.choose_r(top + 2, ratio) + 2
    scope_of = np.array(scopes if scopes else [0] * n_channels, np.int64)
    models: dict = {"pulses": {"coder": tans.join_models([tans.fit(x, r) for x in symbols]), "escape": top + 1, "scope_of": scope_of, "many": many, "sparse": sparse}}
    rows = adaptive_bins(values.where("vtype <> 'pulses'"), ["scope", "vtype"], share=share).orderBy("vtype", "scope", "bin_start").collect()  # some hundred bins each
    for t in NUMERIC:
        bins = [[] for _ in range(many)]
        for x in rows:
            if x["vtype"] == t:
                bins[x["scope"]].append((x["bin_start"], x["bin_width"], x["n"]))
        for k, b in enumerate(bins):
            b = b or [(0, 0, 1)]
            end = b[-1][0] + (1 << b[-1][1])
            bins[k] = [(b[0][0] - (1 << TAIL), TAIL, 0), *b, (end, TAIL, 0)]
        r = max(tans.choose_r(len(b), ratio) for b in bins)
        coder = tans.join_models([tans.fit([max(1, x[2]) for x in b], r) for b in bins])
        flat = [x for b in bins for x in b]
        models[t] = {"coder": coder, "starts": np.array([x[0] for x in flat]), "widths": np.array([x[1] for x in flat]), "many": many, "scope_of": scope_of}
    return models


def pack_bits(values: np.ndarray, widths: np.ndarray) -> bytes:
    """Low bits of values, most significant first, one after the other."""
    ends = np.cumsum(widths)
    total = int(ends[-1]) if len(ends) else 0
    owner = np.repeat(np.arange(len(values)), widths)
    place = np.arange(total) - np.repeat(ends - widths, widths)
    return np.packbits(((values[owner] >> (widths[owner] - 1 - place)) & 1).astype(np.uint8)).tobytes()


def unpack_bits(data: bytes, widths: np.ndarray) -> np.ndarray:
    ends = np.cumsum(widths)
    total = int(ends[-1]) if len(ends) else 0
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[:total].astype(np.int64)
    owner = np.repeat(np.arange(len(widths)), widths)
    place = np.arange(total) - np.repeat(ends - widths, widths)
    out = np.zeros(len(widths), np.int64)
    np.add.at(out, owner, bits << (widths[owner] - 1 - place))
    return out


def _symbols(model: dict, v: np.ndarray, scope: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols (numbered through the scopes), raw values and raw widths of values."""
    first = model["coder"]["first"]
    if "escape" in model:
        e = model["escape"]
        s = np.minimum(v, e)
        word, width = expgolomb_words(np.maximum(v - e, 0))
        return s + first[scope], word, np.where(s == e, width, 0)
    edges = [*first.tolist(), len(model["starts"])]
    s = np.zeros(len(v), np.int64)
    for k in np.unique(scope).tolist() if model["many"] > 1 else range(1):
        own = scope == k if model["many"] > 1 else slice(None)
        s[own] = edges[k] + np.searchsorted(model["starts"][edges[k] : edges[k + 1]], v[own], "right") - 1
    raw = v - model["starts"][s]
    if ((s < first[scope]) | (raw < 0) | (raw >> model["widths"][s] > 0)).any():
        raise ValueError("a value is beyond the end bins")
    return s, raw, model["widths"][s]


def expgolomb_words(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of 0 and above (below 2**52) as words for `pack_bits`: as many zeros first as bits follow the first one."""
    return v + 1, 2 * np.frexp((v + 1).astype(float))[1] - 1


def read_expgolomb(raw: bytes, count: int) -> np.ndarray:
    """`count` Exp-Golomb words."""
    bits = np.unpackbits(np.frombuffer(raw, np.uint8))
    ones, at, out = np.flatnonzero(bits), 0, np.zeros(count, np.int64)
    for k in range(count):
        lead = int(ones[np.searchsorted(ones, at)])
        end = 2 * lead - at + 1
        out[k] = int("".join(map(str, bits[lead:end].tolist())), 2) - 1
        at = end
    return out


def pack_places(places: np.ndarray) -> bytes:
    """Rising numbers: a byte with the width of their low bits, these, and the high parts as a bitmap in which each number
    sets the bit of its high part plus those before it. About two bits more than their low bits each."""
    count, last = len(places), int(places[-1]) if len(places) else 0
    width = max(0, ((last + 1) // max(count, 1)).bit_length() - 1)
    bitmap = np.zeros(count + (last >> width), np.uint8)
    bitmap[(places >> width) + np.arange(count)] = 1
    return bytes([width]) + pack_bits(places & ((1 << width) - 1), np.full(count, width)) + np.packbits(bitmap).tobytes()


def unpack_places(data: bytes, count: int) -> tuple[np.ndarray, int]:
    """`count` places, and the bytes that they take."""
    width, low = data[0], 1 + (count * data[0] + 7) // 8
    ones = np.flatnonzero(np.unpackbits(np.frombuffer(data[low:], np.uint8)))[:count]
    places = ((ones - np.arange(count)) << width) | unpack_bits(data[1:low], np.full(count, width))
    return places, low + (int(ones[-1]) // 8 + 1 if count else 0)


def pack_refs(refs: np.ndarray, used: np.ndarray) -> bytes:
    """Reference times: the first in 64 bits, then zig-zag differences of equal width; unused ones repeat the last."""
    last = np.maximum.accumulate(np.where(used, np.arange(len(refs)), -1))
    first = refs[used][0] if used.any() else 0
    filled = np.where(last >= 0, refs[np.maximum(last, 0)], first)
    step = np.diff(filled)
    zigzag = ((step << 1) ^ (step >> 63)).view(np.uint64)
    width = int(zigzag.max(initial=0)).bit_length()
    return struct.pack("<qB", int(filled[0]), width) + pack_bits(zigzag.view(np.int64), np.full(len(step), width))


def unpack_refs(data: bytes, n: int) -> np.ndarray:
    first, width = struct.unpack_from("<qB", data)
    zigzag = unpack_bits(data[9:], np.full(n - 1, width)).view(np.uint64)
    step = (zigzag >> np.uint64(1)).view(np.int64) ^ -(zigzag & np.uint64(1)).view(np.int64)
    return np.cumsum(np.concatenate([[first], step]))


def frame_values(event, channel, rise, fall, lo: int, n_events: int, n_channels: int, sparse: bool = False) -> tuple[bytes, dict[str, np.ndarray], dict[str, np.ndarray]]:
    """References by event and the four streams of a frame's hits, with the channel of each value and the places of the
    numbers of pulses."""
    order = np.lexsort((fall, rise, channel, event))
    e, c, r, f = (np.asarray(x, np.int64)[order] for x in (event, channel, rise, fall))
    key = (e - lo) * n_channels + c
    active, pulses = np.unique(key, return_counts=True) if sparse else (np.arange(n_events * n_channels), np.bincount(key, minlength=n_events * n_channels))
    refs = np.full(n_events, np.iinfo(np.int64).max)
    np.minimum.at(refs, e - lo, r)
    first = np.concatenate([[True], key[1:] != key[:-1]])[: len(key)]
    gap = np.concatenate([[0], r[1:] - f[:-1]])[: len(key)]
    streams = {"pulses": pulses, "start": (r - refs[e - lo])[first], "width": f - r, "distance": gap[~first]}
    return pack_refs(refs, refs != np.iinfo(np.int64).max), streams, {"pulses": active % n_channels, "start": c[first], "width": c, "distance": c[~first], "places": active}


def _channels(pulses: np.ndarray, n_channels: int, places: np.ndarray | None = None) -> dict[str, np.ndarray]:
    """The channel of each value of a frame, from its numbers of pulses (of all places, or of those given)."""
    active = np.flatnonzero(pulses) if places is None else places
    c, n = active % n_channels, pulses[active] if places is None else pulses
    return {"start": c, "width": np.repeat(c, n), "distance": np.repeat(c, n - 1)}


def frame_hits(refs: np.ndarray, v: dict[str, np.ndarray], lo: int, n_channels: int) -> tuple[np.ndarray, ...]:
    """event, channel, rise, fall of a frame's streams."""
    p, active = v["pulses"], v.get("places")
    active, n = (np.flatnonzero(p), p[np.flatnonzero(p)]) if active is None else (active, p)
    key = np.repeat(active, n)
    ends = np.cumsum(n)
    first = np.zeros(len(key), bool)
    first[ends - n] = True
    step = np.zeros(len(key), np.int64)  # from the fall before (or the reference) to this rise
    step[first], step[~first] = v["start"], v["distance"]
    move = step + np.concatenate([[0], v["width"][:-1]]) if len(key) else step
    move[first] = step[first]
    run = np.cumsum(move)
    base = np.repeat(run[ends - n] - step[ends - n], n) if len(key) else run
    rise = refs[key // n_channels] + run - base
    return lo + key // n_channels, key % n_channels, rise, rise + v["width"]


def encode(hits: DataFrame, models: dict, n_channels: int, events_per_frame: int = 64, backward: bool = False, hide: bool = False, by: str | None = None) -> DataFrame:
    """Frames of hits. hide: the low bits of the number of hits are the coder's start state of the pulses.

    by: a column of numbers that keeps hits in frames of their own and comes first in the result."""
    row = F.struct("event", "channel", "rise", "fall")
    part = F.col(by).cast("long") if by else F.lit(0).cast("long")
    grouped = hits.groupBy(part.alias("_by"), div(F.col("event"), events_per_frame).alias("frame")).agg(F.collect_list(row).alias("hits"))

    def apply(batches):
        for batch in batches:
            for begin in range(0, batch.num_rows, 4096):
                some = batch.slice(begin, 4096)
                frames = some.column(1).to_numpy()
                lists = some.column(2)
                offsets = np.asarray(lists.offsets)
                flat = lists.values
                e, c, r, f = (np.asarray(flat.field(k)) for k in range(4))
                made = []
                for k, frame in enumerate(frames.tolist()):
                    at = slice(offsets[k], offsets[k + 1])
                    made.append(frame_values(e[at], c[at], r[at], f[at], frame * events_per_frame, events_per_frame, n_channels, models["pulses"]["sparse"]))
                n_hits = np.diff(offsets)
                columns = {"_by": some.column(0), "frame": frames, "lo_event": frames * events_per_frame, "hi_event": (frames + 1) * events_per_frame - 1, "n_hits": n_hits, "refs": [m[0] for m in made]}
                for t in TYPES:
                    sizes = [len(m[1][t]) for m in made]
                    cuts = np.cumsum(sizes)[:-1]
                    scope = models[t]["scope_of"][np.concatenate([m[2][t] for m in made])]
                    parts = [np.split(x, cuts) for x in _symbols(models[t], np.concatenate([m[1][t] for m in made]), scope)]
                    size = 1 << models[t]["coder"]["r"]
                    start = [size + int(n) % size for n in n_hits] if hide and t == "pulses" else None
                    out = tans.encode_frames(parts[0], models[t]["coder"], start, backward)
                    columns |= {f"{t}_n": sizes, f"{t}_state": [o[2] for o in out], f"{t}_bits": [o[1] for o in out], f"{t}_payload": [o[0] for o in out], f"{t}_raw": [(pack_places(m[2]["places"]) if t == "pulses" and models[t]["sparse"] else b"") + pack_bits(x, w) for m, x, w in zip(made, parts[1], parts[2])]}
                columns["crc"] = [zlib.crc32(b"".join(columns[name][k] for name in ("refs", *(f"{t}_{p}" for t in TYPES for p in ("payload", "raw"))))) for k in range(len(frames))]
                kinds = {"refs": pa.binary(), **{f"{t}_{p}": pa.binary() for t in TYPES for p in ("payload", "raw")}, **{f"{t}_state": pa.int32() for t in TYPES}}
                yield pa.RecordBatch.from_arrays([pa.array(columns[n], kinds.get(n, pa.int64())) for n in ["_by", *NAMES]], ["_by", *NAMES])

    made = grouped.mapInArrow(apply, "_by long, " + FRAME)
    return made.withColumnRenamed("_by", by) if by else made.drop("_by")


def _streams(get: dict, models: dict, n_channels: int, types: tuple[str, ...], backward: bool = False) -> dict[str, tuple[list[np.ndarray], list[np.ndarray]]]:
    """Symbols and raw numbers of some value types of frames; the pulses as they are, where others need their channels,
    and of sparse frames their places."""
    out: dict = {}
    places: list = [None] * len(get[f"{types[0]}_n"])
    channels: list[dict] = []
    for t in types:
        m = models[t]
        which = None
        raws = get[f"{t}_raw"]
        if t == "pulses" and m["sparse"]:
            found = [unpack_places(raw, n) for raw, n in zip(raws, get["pulses_n"])]
            places, raws = [x[0] for x in found], [raw[x[1] :] for raw, x in zip(raws, found)]
            out["places"] = (places, places)
        if m["many"] > 1:
            scope = [(np.arange(n) if at is None else at) % n_channels for n, at in zip(get[f"{t}_n"], places)] if t == "pulses" else [c[t] for c in channels]
            which = [m["scope_of"][c] for c in scope]
        symbols, _ = tans.decode_frames(list(zip(get[f"{t}_payload"], get[f"{t}_bits"], get[f"{t}_state"], get[f"{t}_n"])), m["coder"], backward, which)
        if t == "pulses":
            if which is not None:
                symbols = [s - m["coder"]["first"][w] for s, w in zip(symbols, which)]
            pulses = []
            for s, raw in zip(symbols, raws):
                more = s == m["escape"]
                s = s.copy()
                if more.any():
                    s[more] += read_expgolomb(raw, int(more.sum()))
                pulses.append(s)
            channels = [_channels(p, n_channels, at) for p, at in zip(pulses, places)]
            out[t] = (symbols, pulses)
        else:
            out[t] = (symbols, [unpack_bits(raw, m["widths"][s]) for s, raw in zip(symbols, raws)])
    return out


def decode_rows(batch: pa.RecordBatch, models: dict, n_channels: int, backward: bool = False) -> list[tuple[np.ndarray, ...]]:
    """Hits of each frame of a batch."""
    get = {n: batch.column(batch.schema.get_field_index(n)).to_pylist() for n in NAMES}
    found = _streams(get, models, n_channels, TYPES, backward)
    out = []
    for k in range(batch.num_rows):
        v = {t: models[t]["starts"][found[t][0][k]] + found[t][1][k] for t in NUMERIC} | {t: found[t][1][k] for t in ("pulses", "places") if t in found}
        refs = unpack_refs(get["refs"][k], get["hi_event"][k] - get["lo_event"][k] + 1)
        out.append(frame_hits(refs, v, get["lo_event"][k], n_channels))
    return out


def decode(frames: DataFrame, models: dict, n_channels: int, backward: bool = False) -> DataFrame:
    """The hits of frames."""

    def apply(batches):
        for batch in batches:
            rows = decode_rows(batch, models, n_channels, backward)
            if rows:
                e, c, r, f = (np.concatenate([x[k] for x in rows]) for k in range(4))
                yield pa.RecordBatch.from_arrays([pa.array(e), pa.array(c.astype(np.int32)), pa.array(r), pa.array(f)], ["event", "channel", "rise", "fall"])

    return frames.select(*NAMES).mapInArrow(apply, "event long, channel int, rise long, fall long")


def hidden(frames: DataFrame, models: dict, backward: bool = False) -> DataFrame:
    """frame, state: what the start state of the pulses carried."""
    m, scope_of = models["pulses"]["coder"], models["pulses"]["scope_of"]

    def apply(batches):
        for batch in batches:
            get = batch.to_pydict()
            places = [unpack_places(raw, n)[0] if models["pulses"]["sparse"] else np.arange(n) for raw, n in zip(get["pulses_raw"], get["pulses_n"])]
            which = [scope_of[at % len(scope_of)] for at in places] if models["pulses"]["many"] > 1 else None
            _, starts = tans.decode_frames(list(zip(get["pulses_payload"], get["pulses_bits"], get["pulses_state"], get["pulses_n"])), m, backward, which)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s - (1 << m["r"]) for s in starts], pa.int64())], ["frame", "state"])

    return frames.select("frame", "pulses_n", "pulses_state", "pulses_bits", "pulses_payload", "pulses_raw").mapInArrow(apply, "frame long, state long")


def frame_crc() -> "F.Column":
    return F.crc32(F.concat("refs", *[f"{t}_{p}" for t in TYPES for p in ("payload", "raw")]))


def verify(frames: DataFrame) -> DataFrame:
    """Adds ok: does the checksum hold. Frames that fail are dropped whole by `sound`."""
    return frames.withColumn("ok", frame_crc() == F.col("crc"))


def sound(frames: DataFrame) -> DataFrame:
    return verify(frames).where("ok").drop("ok")


def write_frames(frames: DataFrame, path: str) -> None:
    """Frames in order of events: files and row groups can be skipped by lo_event. They are coded once, and the ranges
    drawn from what is written."""
    frames = materialise(frames, "frames-coded")
    frames.repartitionByRange("lo_event").sortWithinPartitions("lo_event").write.mode("overwrite").parquet(path)


def read_frames(spark, path: str, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """Frames that can hold events lo..hi: the filters reach the Parquet scan."""
    f = spark.read.schema(FRAME).parquet(path)
    if lo is not None:
        f = f.where(F.col("hi_event") >= lo)
    return f if hi is None else f.where(F.col("lo_event") <= hi)


def flip_bits(frames: DataFrame, every: int, column: str = "width_payload") -> DataFrame:
    """Frames whose number is divisible by `every` with one bit of a column turned."""

    def apply(batches):
        for batch in batches:
            at = batch.schema.get_field_index(column)
            data = [bytes([x[0] ^ 0x10]) + x[1:] if x and frame % every == 0 else x for frame, x in zip(batch.column(0).to_pylist(), batch.column(at).to_pylist())]
            yield batch.set_column(at, column, pa.array(data, pa.binary()))

    return frames.select(*NAMES).mapInArrow(apply, FRAME)


def realised_cost(frames: DataFrame) -> DataFrame:
    """vtype, n_values, coded_bits, raw_bytes of what frames hold."""
    each = F.array(*[F.struct(F.lit(t).alias("vtype"), F.col(f"{t}_n").alias("n"), F.col(f"{t}_bits").alias("b"), F.octet_length(f"{t}_raw").cast("long").alias("r")) for t in TYPES])
    return frames.select(F.inline(each)).groupBy("vtype").agg(F.sum("n").alias("n_values"), F.sum("b").alias("coded_bits"), F.sum("r").alias("raw_bytes"))


def overheads(frames: DataFrame, models: dict) -> DataFrame:
    """frames, reference, state and checksum bits: what value costs leave out."""
    states = sum(models[t]["coder"]["r"] for t in TYPES)
    g = frames.agg(F.count(F.lit(1)).alias("frames"), (F.sum(F.octet_length("refs")) * 8).cast("long").alias("reference_bits"))
    return g.withColumn("state_bits", F.col("frames") * states).withColumn("crc_bits", F.col("frames") * 32)


def frames_with_events(frames: DataFrame, models: dict, n_channels: int, lo: int, hi: int) -> DataFrame:
    """Hits of events lo..hi: whole frames are skipped by their range, the rest filtered after decoding."""
    some = frames.where((F.col("hi_event") >= lo) & (F.col("lo_event") <= hi))
    return decode(some, models, n_channels).where(F.col("event").between(lo, hi))


def count_at_least(frames: DataFrame, models: dict, vtype: str, least: int, n_channels: int = 1) -> DataFrame:
    """n: values of a type that are at least `least`, decided by bins; only a bin that holds it reads raw bits.

    With models by channel the numbers of pulses are read too, as they tell each value's channel (n_channels)."""
    m = models[vtype]
    types = ("pulses", vtype) if m["many"] > 1 else (vtype,)
    above = m["starts"] >= least
    split = ~above & (least - m["starts"] >> m["widths"] == 0)
    names = [f"{t}_{p}" for t in types for p in ("n", "state", "bits", "payload", "raw")]

    def apply(batches):
        for batch in batches:
            total = 0
            for s, raw in zip(*_streams(batch.to_pydict(), models, n_channels, types)[vtype]):
                edge = split[s]
                total += int(above[s].sum()) + int((m["starts"][s[edge]] + raw[edge] >= least).sum())
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    return frames.select(*names).mapInArrow(apply, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def encode_by_unit(hits: DataFrame, units: DataFrame, models: dict, n_channels: int, events_per_frame: int = 64) -> DataFrame:
    """Frames of each acquisition unit (disjoint sets of channels) in one plan: unit_id and the frame's columns."""
    return encode(hits.join(units.select("channel", "unit_id"), "channel"), models, n_channels, events_per_frame, by="unit_id")


def merge_units(frames: DataFrame) -> DataFrame:
    """A packet for each frame number: its units' frames, in order of unit."""
    row = F.struct("unit_id", *NAMES)
    return frames.groupBy("frame").agg(F.array_sort(F.collect_list(row)).alias("units"), F.sum("n_hits").alias("n_hits"))


def split_units(packets: DataFrame) -> DataFrame:
    return packets.select(F.inline("units"))
