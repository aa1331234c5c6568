"""Named queries over the given tables: each is name(spark, sf_dir) -> DataFrame."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.functions import bits as B
from hitcodec.operators import bins as BN
from hitcodec.operators import frames as FR
from hitcodec.operators import histo as H
from hitcodec.operators import hygiene as HY
from hitcodec.operators import layout as L
from hitcodec.operators import models as M
from hitcodec.operators import prefix as PX
from hitcodec.operators import rangecoder as RC
from hitcodec.operators import tans as T
from hitcodec.operators import ticks as TK
from hitcodec.plans import cost as C
from hitcodec.plans import workloads as W
from hitcodec.session import materialise, scratch, ship_package
from hitcodec.sources import views as V
from hitcodec.sources.tables import load

QUERIES: dict = {}
CH = V.CHANNELS


def query(f):
    QUERIES[f.__name__] = f
    return f


def named(name: str, f):
    QUERIES[name] = f


def hits(view: str, spark, sf) -> DataFrame:
    return V.HITS[view](spark, sf)


# --- representation


@query
def tick_split(spark, sf):
    return TK.split_tick(hits("LI1", spark, sf), "rise").select("event", "channel", "rise", "fine", "coarse", "epoch")


@query
def tick_join(spark, sf):
    return TK.join_tick(TK.split_tick(hits("EV1", spark, sf), "rise").drop("rise"), "rise").select("event", "channel", "rise", "fall")


@query
def ref_min(spark, sf):
    h = TK.with_reference(hits("EV1", spark, sf))
    return h.select("event", "channel", "ref", (F.col("rise") - F.col("ref")).alias("rel"))


@query
def ref_channel(spark, sf):
    h = TK.with_reference(hits("EV1", spark, sf), "channel", ref_channel=3)
    return h.select("event", "channel", "ref", (F.col("rise") - F.col("ref")).alias("rel"))


@query
def ref_coarse(spark, sf):
    h = TK.quantise_reference(TK.with_reference(hits("EV1", spark, sf)), 16)
    return h.select("event", "channel", "ref", (F.col("rise") - F.col("ref")).alias("rel"))


@query
def zigzag_roundtrip(spark, sf):
    h = TK.with_reference(hits("EV1", spark, sf), "channel", ref_channel=3).withColumn("rel", F.col("rise") - F.col("ref"))
    return h.withColumn("z", B.zigzag("rel")).select("event", "channel", B.unzigzag("z").alias("rel"), "z")


@query
def edge_rejects(spark, sf):
    return HY.judge_edges(V.ev2(spark, sf), max_width=10**12).groupBy("reason").agg(F.count(F.lit(1)).alias("edges"))


@query
def edge_pairs(spark, sf):
    return HY.pair_edges(V.ev2(spark, sf))


@query
def edge_diagnostics(spark, sf):
    return HY.diagnostics(V.ev2(spark, sf))


@query
def exception_words(spark, sf):
    return HY.exception_words(HY.filter_edges(V.ev2(spark, sf))[1])


@query
def encode_modes(spark, sf):
    e = V.ev2(spark, sf)
    one = lambda m: HY.encode_mode(e, m).agg(F.sum("edges").alias("edges")).select(F.lit(m).alias("mode"), "edges")
    return one("main").unionByName(one("diagnostic"))


def _records(view):
    def f(spark, sf):
        r = L.to_channel_records(hits(view, spark, sf))
        text = lambda c: F.array_join(F.transform(c, lambda x: x.cast("string")), ",")
        return r.select("event", "channel", "ref", "pulses", "start", text("widths").alias("widths"), text("distances").alias("distances"))

    return f


def _records_roundtrip(view):
    return lambda spark, sf: L.from_channel_records(L.to_channel_records(hits(view, spark, sf)))


for _v in V.HITS:
    named(f"channel_records_{_v.lower()}", _records(_v))
    named(f"records_roundtrip_{_v.lower()}", _records_roundtrip(_v))
    named(f"value_streams_{_v.lower()}", lambda spark, sf, v=_v: L.value_streams(hits(v, spark, sf)))
    named(f"pulse_frequencies_{_v.lower()}", lambda spark, sf, v=_v: L.pulse_frequencies(hits(v, spark, sf), CH))
    named(f"counts_per_event_{_v.lower()}", lambda spark, sf, v=_v: L.counts_per_event(hits(v, spark, sf)))
    named(f"ecdf_{_v.lower()}", lambda spark, sf, v=_v: H.ecdf(L.value_streams(hits(v, spark, sf)).where("vtype <> 'pulses'")))
    named(f"cost_raw_words_{_v.lower()}", lambda spark, sf, v=_v: C.cost_raw_words(hits(v, spark, sf)))
    for _n, _f in (("fixed", C.cost_fixed), ("expgolomb", C.cost_expgolomb), ("unary", C.cost_unary)):
        named(f"cost_{_n}_{_v.lower()}", lambda spark, sf, v=_v, f=_f: f(C.counted(hits(v, spark, sf), CH)))
    named(f"cost_entropy_{_v.lower()}", lambda spark, sf, v=_v: C.cost_entropy(C.counted(hits(v, spark, sf), CH)))
    named(f"ladder_{_v.lower()}", lambda spark, sf, v=_v: C.ladder(hits(v, spark, sf)))


@query
def ladder_ratio(spark, sf):
    return C.with_ratio(C.ladder(hits("OR1", spark, sf), rungs=("R0", "R1", "R1b", "R3")))


def _styles(spark, sf):
    h = hits("EV1", spark, sf)
    a, b, c = (L.pulse_count_symbols(h, s, CH) for s in ("count", "flag", "bitmap"))
    return a.unionByName(b).unionByName(c)


named("pulse_count_styles", _styles)
named("fixed_packet_bits", lambda spark, sf: L.pack_fixed(hits("OR1", spark, sf), CH).select("event", F.length("packet").alias("bits")))
named("fixed_packet_roundtrip", lambda spark, sf: L.unpack_fixed(L.pack_fixed(hits("LI1", spark, sf), CH, (4, 36, 27, 36)), CH, (4, 36, 27, 36)))
named("word_packet_bits", lambda spark, sf: L.pack_words(hits("OR1", spark, sf)).select("event", (F.size("words") * 32).alias("bits")))
named("word_packet_roundtrip", lambda spark, sf: L.unpack_words(L.pack_words(hits("EV1", spark, sf))))


# --- symbol coders


def or0_hist(spark, sf) -> DataFrame:
    return V.or0(spark, sf).groupBy(F.col("pulses").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n"))


ALPHABET = 100_000


def counts_of(hist: DataFrame) -> dict[int, int]:
    """A small alphabet's counts: the driver's input for fitting. More than `ALPHABET` symbols are an error, never cut."""
    rows = hist.limit(ALPHABET + 1).collect()
    if len(rows) > ALPHABET:
        raise ValueError(f"an alphabet of more than {ALPHABET} symbols; bin it first")
    return {int(r["v"]): int(r["n"]) for r in sorted(rows, key=lambda r: r["v"])}


@query
def pulse_coders(spark, sf):
    """The table of coders for the numbers of pulses, in bits a value."""
    return W.pulse_coder_table(or0_hist(spark, sf))


named("expgolomb_codes", lambda spark, sf: load(spark, sf, "part").select(F.col("p_size").cast("long").alias("v")).distinct().select("v", B.expgolomb_encode("v").alias("word"), B.expgolomb_bits("v").alias("bits")))
named("expgolomb_roundtrip", lambda spark, sf: V.or0(spark, sf).select("event", "channel", B.expgolomb_encode("pulses").alias("word")).select("event", "channel", B.expgolomb_decode("word").alias("pulses")))
named("unary_roundtrip", lambda spark, sf: V.or0(spark, sf).select("event", "channel", B.unary_encode("pulses").alias("word")).select("event", "channel", B.unary_decode("word").alias("pulses")))


@query
def radix_roundtrip(spark, sf):
    """Line numbers of an order as base-8 numbers, in blocks, and back."""
    m = 8
    d = load(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("event")).agg(F.array_sort(F.collect_list(F.col("l_linenumber").cast("long") % m)).alias("d"))
    size = B.radix_block(m)
    parts = F.transform(F.sequence(F.lit(0), F.expr(f"(size(d) - 1) div {size}")), lambda k: F.slice("d", (k * size + 1).cast("int"), size))
    packed = d.select("event", F.explode(parts).alias("part")).select("event", B.radix_pack("part", m).alias("packed"), F.size("part").alias("n"))
    return packed.select("event", F.explode(B.radix_unpack("packed", "n", m)).alias("digit"))


@query
def cost_radix(spark, sf):
    return C.cost_radix(or0_hist(spark, sf).withColumn("vtype", F.lit("pulses")), 9).select("vtype", "n_values", F.round("bits", 3).alias("bits"))


def _huffman_total(hist: DataFrame) -> DataFrame:
    h = BN.simple_huffman(hist.withColumn("vtype", F.lit("x")), ["vtype"], top_bits=40)
    return h.select("n_values", F.col("n_bins").alias("symbols"), "coded_bits")


named("cost_huffman_pulses", lambda spark, sf: _huffman_total(or0_hist(spark, sf)))
named("cost_huffman_quantity", lambda spark, sf: _huffman_total(load(spark, sf, "lineitem").groupBy(F.col("l_quantity").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n"))))


def char_hist(frames: DataFrame) -> DataFrame:
    return frames.select(F.explode("syms").alias("v")).groupBy(F.col("v").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n"))


named("cost_huffman_bytes", lambda spark, sf: _huffman_total(char_hist(V.do1(spark, sf))))


@query
def huffman_kraft(spark, sf):
    """For two codebooks: symbols, Kraft sum, pairs of words of which one begins the other."""
    out = None
    for name, hist in (("pulses", or0_hist(spark, sf)), ("characters", char_hist(V.do1(spark, sf)))):
        book = PX.codebook(spark, PX.canonical_codes(PX.huffman_lengths(counts_of(hist))))
        one = book.agg(F.round(F.sum(F.pow(F.lit(2.0), -F.col("len"))), 6).alias("kraft")).crossJoin(PX.prefix_clashes(book).agg(F.count(F.lit(1)).alias("clashes"))).select(F.lit(name).alias("code"), "kraft", "clashes")
        out = one if out is None else out.unionByName(one)
    return out


def _stream_codec(frames: DataFrame, code, decode) -> DataFrame:
    """frame, pos, sym after coding and decoding every frame's symbols (arrays) in Arrow batches.

    Frames of like length step together, and only so many that their grid of symbols stays small."""

    def apply(batches):
        for batch in batches:
            lists = batch.column(1)
            offsets, flat = np.asarray(lists.offsets), np.asarray(lists.values)
            sizes, frames_of = np.diff(offsets), np.asarray(batch.column(0))
            for group in _groups(sizes):
                syms = [flat[offsets[k] : offsets[k + 1]].astype(np.int64) for k in group]
                yield from coded(frames_of[group], syms)

    def coded(frames_of, syms):
        back = decode(code(syms), [len(s) for s in syms])
        n = [len(b) for b in back]
        frame = np.repeat(frames_of, n)
        yield pa.RecordBatch.from_arrays([pa.array(frame, pa.int64()), pa.array(np.concatenate([np.arange(k) for k in n] or [np.zeros(0, np.int64)]), pa.int64()), pa.array(np.concatenate(back) if back else np.zeros(0, np.int64), pa.int64())], ["frame", "pos", "sym"])

    return frames.select("frame", "syms").mapInArrow(apply, "frame long, pos long, sym long")


def _groups(sizes: np.ndarray, cells: int = 1 << 20) -> list[np.ndarray]:
    """Places of frames by falling length, cut so that frames times the longest is at most `cells` (or one frame)."""
    order, out, at = np.argsort(-sizes, kind="stable"), [], 0
    while at < len(order):
        step = max(1, cells // max(1, int(sizes[order[at]])))
        out.append(order[at : at + step])
        at += step
    return out


def or0_frames(spark, sf) -> DataFrame:
    """Numbers of pulses in frames of 16 orders."""
    rows = V.or0(spark, sf).withColumn("frame", V.div(F.col("event"), 16))
    return rows.groupBy("frame").agg(F.array_sort(F.collect_list(F.struct("event", "channel", "pulses"))).alias("r")).select("frame", F.transform("r", lambda x: x["pulses"].cast("long")).alias("syms"))


def lb1_frames(spark, sf) -> DataFrame:
    return V.lb1(spark, sf).groupBy("frame").agg(F.array_sort(F.collect_list(F.struct("pos", "sym"))).alias("r")).select("frame", F.transform("r", lambda x: x["sym"].cast("long")).alias("syms"))


def do1_frames(spark, sf) -> DataFrame:
    return V.do1(spark, sf).select("frame", F.transform("syms", lambda x: x.cast("short")).alias("syms"))  # at most 256


def frame_hist(frames: DataFrame) -> dict[int, int]:
    return counts_of(frames.select(F.explode("syms").alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("n")))


def dense_counts(counts: dict[int, int]) -> list[int]:
    return [max(1, counts.get(k, 0)) for k in range(max(counts) + 1)]


def _tans_roundtrip(source, ratio=8, backward=False, payload=False):
    def f(spark, sf):
        ship_package(spark)
        frames = source(spark, sf)
        counts = frame_hist(frames)
        model = T.fit(dense_counts(counts), T.choose_r(max(2, len(counts)), ratio) + 1)
        size = 1 << model["r"]

        def code(syms):
            start = [size + len(s) % size for s in syms] if payload else None
            return T.encode_frames(syms, model, start, backward)

        def decode(coded, lengths):
            out, starts = T.decode_frames([(*c, n) for c, n in zip(coded, lengths)], model, backward)
            if payload and [s - size for s in starts] != [n % size for n in lengths]:
                raise ValueError("the start state does not hold its data")
            return out

        return _stream_codec(frames, code, decode)

    return f


named("tans_roundtrip_pulses", _tans_roundtrip(or0_frames))
named("tans_roundtrip_binary", _tans_roundtrip(lb1_frames))
named("tans_roundtrip_characters", _tans_roundtrip(do1_frames))
named("tans_roundtrip_backward", _tans_roundtrip(or0_frames, backward=True))
named("tans_roundtrip_payload", _tans_roundtrip(or0_frames, payload=True))


@query
def huffman_roundtrip(spark, sf):
    ship_package(spark)
    frames = do1_frames(spark, sf)
    codes = PX.canonical_codes(PX.huffman_lengths(frame_hist(frames), 15))
    return _stream_codec(frames, lambda s: [PX.encode_bits(x, codes) for x in s], lambda c, n: [PX.decode_bits(b[0], k, codes) for b, k in zip(c, n)])


named("cost_huffman_pages", lambda spark, sf: _huffman_total(char_hist(V.pg1(spark, sf))))


@query
def near_uniform_control(spark, sf):
    """Part sizes, of which no coder gains much: entropy beside the bits of equal chances."""
    h = load(spark, sf, "part").groupBy(F.lit("p_size").alias("vtype"), F.col("p_size").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    return C.cost_entropy(h).withColumn("even", F.round(F.log2("symbols"), 4))


@query
def escape_roundtrip(spark, sf):
    """Numbers of pulses with an alphabet of 0..3: larger ones as an escape symbol and their excess as an Exp-Golomb word."""
    ship_package(spark)
    frames = or0_frames(spark, sf)
    counts, escape = PX.with_escape(frame_hist(frames), 3)
    codes = PX.canonical_codes(PX.huffman_lengths(counts))
    code = lambda syms: [(PX.encode_bits(np.minimum(s, escape), codes)[0], FR.pack_bits(*FR.expgolomb_words(s[s >= escape] - escape))) for s in syms]

    def decode(coded, lengths):
        out = []
        for (data, excess), n in zip(coded, lengths):
            s = PX.decode_bits(data, n, codes).copy()
            s[s == escape] += FR.read_expgolomb(excess, int((s == escape).sum()))
            out.append(s)
        return out

    return _stream_codec(frames, code, decode)


def _range_roundtrip(source):
    def f(spark, sf):
        ship_package(spark)
        frames = source(spark, sf)
        cum = RC.model(dense_counts(frame_hist(frames)))
        return _stream_codec(frames, lambda s: RC.range_encode(s, cum), lambda c, n: RC.range_decode(c, n, cum))

    return f


named("range_roundtrip_pulses", _range_roundtrip(or0_frames))
named("range_roundtrip_characters", _range_roundtrip(do1_frames))


def _tans_sql(spark, sf):
    """The coder's twin as folds of SQL: forwards with a string of bits, then backwards from its end."""
    frames = lb1_frames(spark, sf)
    counts = frame_hist(frames)
    model = T.fit(dense_counts(counts), 4)
    return sql_decode(sql_encode(frames, model), model)


def sql_encode(frames: DataFrame, model: dict) -> DataFrame:
    size, r = 1 << model["r"], model["r"]
    nb, off, nxt = (F.lit([int(x) for x in model["enc"][k]]) for k in ("nb", "off", "next"))
    at = lambda a, k: F.element_at(a, (k + 1).cast("int"))

    def step(acc, s):
        bits = F.call_function("shiftright", (acc["x"] + at(nb, s)).cast("int"), F.lit(r + 1)).cast("int")
        out = F.when(bits > 0, F.substring(F.lpad(F.bin(acc["x"]), r + 1, "0"), F.lit(r + 2) - bits, bits)).otherwise("")
        to = at(nxt, at(off, s) + F.call_function("shiftright", acc["x"].cast("int"), bits))
        return F.struct(to.cast("long").alias("x"), F.concat(acc["bits"], out).alias("bits"))

    fold = F.aggregate("syms", F.struct(F.lit(size).cast("long").alias("x"), F.lit("").alias("bits")), step)
    return frames.withColumn("f", fold).select("frame", F.size("syms").alias("n"), F.col("f.x").alias("x"), F.col("f.bits").alias("bits"))


def sql_decode(coded: DataFrame, model: dict) -> DataFrame:
    size = 1 << model["r"]
    sym, nbits, base = (F.lit([int(x) for x in model["dec"][k]]) for k in ("sym", "nbits", "base"))
    at = lambda a, k: F.element_at(a, (k - size + 1).cast("int"))
    start = F.struct(F.col("x").alias("x"), F.length("bits").alias("end"), F.array().cast("array<bigint>").alias("out"))

    def step(acc, _):
        n = at(nbits, acc["x"])
        low = F.when(n > 0, F.conv(F.substring(F.col("bits"), acc["end"] - n + 1, n), 2, 10).cast("long")).otherwise(0)
        return F.struct((F.lit(size) + at(base, acc["x"]) + low).cast("long").alias("x"), (acc["end"] - n).cast("int").alias("end"), F.concat(acc["out"], F.array(at(sym, acc["x"]).cast("bigint"))).alias("out"))

    fold = F.aggregate(F.sequence(F.lit(1), F.col("n")), start, step)
    return coded.where("n > 0").select("frame", F.posexplode(F.reverse(fold["out"])).alias("pos", "sym")).select("frame", F.col("pos").cast("long").alias("pos"), "sym")


named("tans_sql_roundtrip", _tans_sql)

EXAMPLE = T.model_of(np.array([0, 1, 0, 0]), 2)

def messages(spark, sf) -> DataFrame:
    """frame, syms: the binary digits of each customer's key, the messages of the examples."""
    c = load(spark, sf, "customer").where("c_custkey is not null")
    return c.select(F.col("c_custkey").alias("frame"), F.transform(F.split(F.bin("c_custkey"), ""), lambda x: x.cast("int")).alias("syms"))


def message_steps(spark, sf) -> DataFrame:
    """c_custkey, step, sym, state, state_bits, bits, next_state: the coder of four states over each message."""
    ship_package(spark)
    names = ["c_custkey", "step", "sym", "state", "state_bits", "bits", "next_state"]
    single = [T.trace([s], EXAMPLE, x)[0] for x in range(4, 8) for s in (0, 1)]  # each step there is: place 2 (x - 4) + s
    held, to = np.array([round(r[3], 4) for r in single]), np.array([r[5] for r in single])
    words = pa.array([r[4] for r in single], pa.string())

    def apply(batches):
        for batch in batches:
            keys, lists = np.asarray(batch.column(0)), batch.column(1)
            offsets, flat = np.asarray(lists.offsets), np.asarray(lists.values)
            sizes, state = np.diff(offsets), np.full(len(keys), 4)
            for k in range(int(sizes.max(initial=0))):
                live = np.flatnonzero(sizes > k)
                sym, x = flat[offsets[live] + k], state[live]
                place = 2 * (x - 4) + sym
                state[live] = to[place]
                columns = [(keys[live], pa.int64()), (np.full(len(live), k), pa.int32()), (sym, pa.int32()), (x, pa.int32()), (held[place], pa.float64()), None, (to[place], pa.int32())]
                yield pa.RecordBatch.from_arrays([pa.array(*c) if c else words.take(pa.array(place)) for c in columns], names)

    return messages(spark, sf).mapInArrow(apply, "c_custkey long, step int, sym int, state int, state_bits double, bits string, next_state int")


def message_shares(spark, sf) -> np.ndarray | None:
    """Shares of the two symbols in all messages; none without messages."""
    counts = frame_hist(messages(spark, sf))
    n = np.array([counts.get(0, 0), counts.get(1, 0)], np.float64)
    return n / n.sum() if n.sum() else None


@query
def tans_tables_example(spark, sf):
    """The decoder's table, with the steps of all messages that end in each of its states."""
    d = EXAMPLE["dec"]
    state = F.col("next_state")
    at = lambda k, more=0: F.element_at(F.lit([int(x) + more for x in d[k]]), state - 3)
    g = message_steps(spark, sf).groupBy("next_state").agg(F.count(F.lit(1)).alias("n"))
    return g.select(state.alias("state"), at("sym").alias("sym"), at("nbits").alias("nbits"), at("base").alias("base"), at("base", 4).alias("next_state"), "n")


@query
def tans_encode_example(spark, sf):
    """Bits and final state of each message, from the coder's lanes."""
    ship_package(spark)
    model, encode = EXAMPLE, T.encode_frames

    def apply(batches):
        for batch in batches:
            for begin in range(0, batch.num_rows, 4096):
                some = batch.slice(begin, 4096)
                syms = [np.array(x, np.int64) for x in some.column(1).to_pylist()]
                out = encode(syms, model, [4] * len(syms))
                bits = ["".join(f"{x:08b}" for x in data)[:n] for data, n, _ in out]
                yield pa.RecordBatch.from_arrays([some.column(0), pa.array(bits, pa.string()), pa.array([o[2] for o in out], pa.int32())], ["c_custkey", "bits", "state"])

    return messages(spark, sf).mapInArrow(apply, "c_custkey long, bits string, state int")


named("tans_trace_example", message_steps)


@query
def tans_stationary_example(spark, sf):
    """Shares of the four states for independent symbols as frequent as in the messages."""
    p = message_shares(spark, sf)
    rho = [] if p is None else T.stationary(EXAMPLE, p)
    return spark.createDataFrame([(k + 4, round(float(x), 4)) for k, x in enumerate(rho)], "state int, share double")


@query
def tans_loss_example(spark, sf):
    """Loss of the four states for such symbols, and whether the best table of eight loses less."""
    p = message_shares(spark, sf)
    rows = []
    if p is not None:
        four = float(T.loss(EXAMPLE, p)["loss"])
        rows = [("L4 example", round(four, 4), bool(T.spread_best(T.quotas(np.maximum(p, 1e-9), 3), 3, p)[1] < four))]
    return spark.createDataFrame(rows, "coder string, loss double, eight_is_less boolean")


def symbol_sets(spark, sf):
    return {"pulses": counts_of(or0_hist(spark, sf)), "toxic": frame_hist(lb1_frames(spark, sf)), "characters": counts_of(char_hist(V.do1(spark, sf)))}


@query
def tans_quota_invariants(spark, sf):
    """For each symbol set: do quotas sum to the table size with at least one each, and does the spread keep them."""
    rows = []
    for name, counts in symbol_sets(spark, sf).items():
        c = [n for _, n in sorted(counts.items())]
        r = T.choose_r(max(2, len(c)))
        q = T.quotas(c, r)
        kept = all((np.bincount(T.spread(q, r, k), minlength=len(q)) == q).all() for k in ("step", "block", "reverse", "precise"))
        rows.append((name, bool(q.sum() == 1 << r), bool(q.min() >= 1), bool(kept)))
    return spark.createDataFrame(rows, "symbols string, sums boolean, positive boolean, kept boolean")


@query
def tans_loss_sweep(spark, sf):
    """symbols, m, r, spread, entropy, loss, table_bytes: the loss over table sizes and spreads."""
    ship_package(spark)
    toxic = lb1_frames(spark, sf).select(F.explode("syms").alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("n"))
    sets = (("pulses", or0_hist(spark, sf)), ("toxic", toxic), ("characters", char_hist(V.do1(spark, sf))))
    every = None
    for name, h in sets:
        one = h.select(F.lit(name).alias("symbols"), "v", "n")
        every = one if every is None else every.unionByName(one)
    return W.tans_loss_sweep(every, [2, 3, 4, 5, 6, 8, 10])


@query
def tans_loss_bounds(spark, sf):
    """What the loss sweep must keep: entropies and table sizes as computed from the data, no gain below the entropy, and
    on a stride a loss that has fallen by more than half from eight states a symbol to the greatest table."""
    p = tans_loss_sweep(spark, sf)
    step = p.where("spread = 'step'").groupBy("symbols").agg(F.sort_array(F.collect_list(F.struct("r", "m", "loss"))).alias("s"))
    wide = F.filter("s", lambda x: x["m"] * 8 <= F.pow(F.lit(2.0), x["r"]))
    falls = step.select("symbols", F.when(F.size(wide) > 1, F.element_at(wide, -1)["loss"] * 2 < F.element_at(wide, 1)["loss"]).otherwise(True).alias("falls"))
    g = p.groupBy("symbols", "m", "r").agg(F.max("entropy").alias("entropy"), F.max("table_bytes").alias("table_bytes"), F.count(F.lit(1)).alias("spreads"), (F.min("loss") > -1e-9).alias("no_gain"))
    return g.join(falls, "symbols").select("symbols", "m", "r", F.round("entropy", 4).alias("entropy"), "table_bytes", "spreads", "no_gain", "falls")


# --- bins


def value_hist(source, spark, sf) -> DataFrame:
    """vtype, v, n of numeric types of a hits view, or of a values view as one type."""
    if source in V.HITS:
        return H.histogram(L.value_streams(hits(source, spark, sf)).where("vtype <> 'pulses'"), ["vtype"])
    values = {"EM0": V.em0, "EM1": V.em1, "CV1": V.cv1, "LI2": V.li2}[source](spark, sf)
    return H.histogram(values.withColumn("vtype", F.lit(source.lower())), ["vtype"])


for _s in ("EV1", "LI1", "OR1", "EM0"):
    named(f"simple_bins_sweep_{_s.lower()}", lambda spark, sf, s=_s: BN.simple_bin_sweep(value_hist(s, spark, sf), ["vtype"], [8, 12, 16, 20, 24]))
    named(f"simple_huffman_{_s.lower()}", lambda spark, sf, s=_s: BN.simple_huffman(value_hist(s, spark, sf), ["vtype"]))
for _s in ("EV1", "LI1", "OR1", "EM0", "EM1", "CV1", "LI2"):
    named(f"adaptive_bins_{_s.lower()}", lambda spark, sf, s=_s: BN.adaptive_bins(value_hist(s, spark, sf), ["vtype"], share=64))
for _s in ("EV1", "LI1", "OR1"):
    named(f"adaptive_sweep_{_s.lower()}", lambda spark, sf, s=_s: BN.adaptive_sweep(value_hist(s, spark, sf), ["vtype"], [16, 64, 256, 1024]))


@query
def adaptive_sketch_regret(spark, sf):
    """Is the cost of bins from quantile sketches within a tenth of the exact greedy bins'."""
    v = L.value_streams(hits("OR1", spark, sf)).where("vtype <> 'pulses'").select("vtype", "v")
    a = BN.bin_cost(BN.adaptive_bins(H.histogram(v, ["vtype"]), ["vtype"], share=128), ["vtype"]).select("vtype", F.col("total").alias("a"))
    b = BN.bin_cost(BN.adaptive_bins_sketch(v, ["vtype"], 128), ["vtype"]).select("vtype", F.col("total").alias("b"))
    return a.join(b, "vtype").select("vtype", (F.col("b") <= F.col("a") * 1.1).alias("close"))


def _or1_width_bins(spark, sf):
    h = value_hist("OR1", spark, sf).where("vtype = 'width'")
    h = materialise(h, "width-values")  # used several times
    return h, materialise(BN.adaptive_bins(h, ["vtype"], share=64), "width-bins")


@query
def bin_lut_vs_join(spark, sf):
    """Values for which the look-up, the nested loop and the cell join disagree: none."""
    h, bins = _or1_width_bins(spark, sf)
    local = bins.orderBy("bin_start").collect()  # some dozen bins
    lut = BN.assign_bin_lut(h, [r["bin_start"] for r in local], [r["bin_width"] for r in local], to="lut")
    a = BN.assign_bin_join(lut, bins).withColumnRenamed("bin", "loop")
    b = BN.assign_bin_range(a, bins)
    return b.agg(F.count(F.lit(1)).alias("values"), F.count_if((F.col("lut") != F.col("loop")) | (F.col("loop") != F.col("bin"))).alias("differ"))


@query
def bin_value_roundtrip(spark, sf):
    h, bins = _or1_width_bins(spark, sf)
    coded = BN.assign_bin_join(h, bins).join(F.broadcast(bins.select("bin", "bin_start")), "bin").select("bin", (F.col("v") - F.col("bin_start")).alias("raw"), "n")
    return BN.value_from_bin(coded, bins).select("v", "n")


@query
def bin_uniformity(spark, sf):
    h, bins = _or1_width_bins(spark, sf)
    return BN.bin_uniformity(h, bins, ["vtype"])


@query
def bins_optimal_regret(spark, sf):
    """Bits of greedy and of optimal bins for part sizes with as many bins at most."""
    h = load(spark, sf, "part").groupBy(F.col("p_size").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n")).orderBy("v").toPandas()
    v, n = h["v"].to_numpy(), h["n"].to_numpy()
    g = BN.greedy_bins(v, n, int(n.sum()) // 8)
    cost = sum(c * (w - np.log2(c / n.sum())) for _, w, c in g if c)
    best, _ = BN.optimal_bins(v, n, len(g))
    return spark.createDataFrame([(bool(best <= cost + 1e-6), bool(cost <= 1.1 * best))], "optimal_not_above boolean, within_tenth boolean")


# --- scopes and further optimisations

for _s, _f in (("EM1", V.em1), ("CV1", V.cv1), ("LI2", V.li2)):
    named(f"scope_channel_{_s.lower()}", lambda spark, sf, f=_f: M.scope_comparison(f(spark, sf), ["global", "channel"], 32))
named("scope_channel_or1", lambda spark, sf: M.scope_comparison(L.value_streams(hits("OR1", spark, sf)).where("vtype = 'width'"), ["global", "channel"], 32))


@query
def scope_class(spark, sf):
    v = L.value_streams(V.li1(spark, sf, None)).where("vtype = 'width'")
    return M.scope_comparison(v, ["global", "class", "unit"], 32, V.hierarchy(spark, sf))


@query
def scope_kclasses(spark, sf):
    """Does a table for each of four merged classes cost between one for all and one for each channel."""
    v = V.em1(spark, sf)
    c = M.scope_comparison(v, ["global", "class", "channel"], 32, M.cluster_channels(v, 4))
    p = c.groupBy().pivot("scope", ["global", "class", "channel"]).agg(F.first("bits_per_value"))
    return p.select((F.col("class") <= F.col("global")).alias("class_helps"), (F.col("channel") <= F.col("class")).alias("channel_helps"))


named("break_even", lambda spark, sf: M.break_even(M.scope_comparison(V.em1(spark, sf), ["global", "channel"], 32)))
for _v in V.HITS:
    named(f"zero_pointer_cost_{_v.lower()}", lambda spark, sf, v=_v: M.zero_pointer_cost(L.value_streams(hits(v, spark, sf))))
named("zero_pointer_by_pulses", lambda spark, sf: M.zero_pointer_cost(L.value_streams(hits("OR1", spark, sf)), True))


@query
def zero_pointer_roundtrip(spark, sf):
    """Starts rebuilt from the pointer and the starts of the other channels."""
    s = L.value_streams(hits("LI1", spark, sf)).where("vtype = 'start'").select("event", "channel", "v")
    p = M.first_channels(L.value_streams(hits("LI1", spark, sf))).select("event", "pointer")
    others = s.join(p, "event").where("channel <> pointer").select("event", "channel", "v")
    return others.unionByName(p.select("event", F.col("pointer").alias("channel"), F.lit(0).cast("long").alias("v")))


named("event_class_entropy", lambda spark, sf: M.class_entropy(V.cu1(spark, sf)))


@query
def channel_mutual_information(spark, sf):
    h = hits("OR1", spark, sf)
    return H.mutual_information(h, load(spark, sf, "orders").count())


@query
def delta_orders(spark, sf):
    """Entropy of order dates (days) as they are and as differences inside a customer; both need few bits."""
    o = load(spark, sf, "orders").select(F.col("o_custkey").alias("k"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1990-01-01").cast("date")).cast("long").alias("day"), F.col("o_orderkey").alias("id"))
    d = H.delta_code(o, "day", ["k"], ["day", "id"])
    long = d.select(F.expr("stack(2, 'value', day, 'delta', delta) as (kind, v)"))
    e = H.entropy(H.histogram(long, ["kind"]), ["kind"])
    return e.select("kind", F.col("total").cast("long").alias("total"), F.round("entropy", 4).alias("bits"))


@query
def delta_roundtrip(spark, sf):
    o = load(spark, sf, "orders").select(F.col("o_custkey").alias("k"), V.cents("o_totalprice").alias("price"), F.col("o_orderkey").alias("id"))
    d = H.delta_code(o, "price", ["k"], ["id"]).drop("price")
    return H.delta_decode(d, ["k"], ["id"], "price").select("k", "id", "price")


@query
def holdout_characters(spark, sf):
    """Bits a character of benchmark texts by the documents' model, and of documents by their own."""
    doc = char_hist(V.do1(spark, sf)).withColumn("k", F.lit(0))
    bm = char_hist(V.bm1(spark, sf)).withColumn("k", F.lit(0))
    one = lambda name, h: M.cross_entropy(doc, h, ["k"]).select(F.lit(name).alias("data"), "n", "bits")
    return one("documents", doc).unionByName(one("benchmark", bm))


@query
def holdout_bins(spark, sf):
    h = hits("OR1", spark, sf)
    return M.holdout_cost(L.value_streams(h).where("vtype <> 'pulses'"), F.col("event") % 2 == 1, 256)


@query
def model_size(spark, sf):
    """Bins and bits of tables for one model and one for each channel, by type."""
    v = L.value_streams(hits("OR1", spark, sf)).where("vtype <> 'pulses'")
    out = None
    for scope in ("global", "channel"):
        h = H.histogram(M.scope_values(v, scope), ["scope_id", "vtype"])
        g = BN.adaptive_bins(h, ["scope_id", "vtype"], share=64).groupBy("vtype").agg(F.count(F.lit(1)).alias("n_bins"))
        one = g.select(F.lit(scope).alias("scope"), "vtype", "n_bins", M.model_bits("n_bins").alias("table_bits"))
        out = one if out is None else out.unionByName(one)
    return out


# --- frames


def framed(view, spark, sf, scopes=None, **options):
    """(hits, models, frames read back from files)."""
    ship_package(spark)
    h = hits(view, spark, sf)
    models = FR.fit_models(h, CH, scopes=scopes)
    path = scratch(spark, f"frames-{view}")
    FR.write_frames(FR.encode(h, models, CH, **options), path)
    return h, models, FR.read_frames(spark, path)


def _frames_roundtrip(view, **options):
    def f(spark, sf):
        _, models, frames = framed(view, spark, sf, **options)
        return FR.decode(FR.sound(frames), models, CH, options.get("backward", False))

    return f


for _v in V.HITS:
    named(f"frames_roundtrip_{_v.lower()}", _frames_roundtrip(_v))
# models of their own for each channel, and for classes of twelve channels
named("frames_roundtrip_channel", _frames_roundtrip("OR1", scopes=list(range(CH))))
named("frames_roundtrip_class", _frames_roundtrip("OR1", scopes=[c // 12 for c in range(CH)]))
named("frames_roundtrip_backward", _frames_roundtrip("EV1", backward=True))
named("frames_roundtrip_small", _frames_roundtrip("EV1", events_per_frame=1))


@query
def frames_hidden_payload(spark, sf):
    _, models, frames = framed("EV1", spark, sf, hide=True)
    size = 1 << models["pulses"]["coder"]["r"]
    return FR.hidden(frames, models).join(frames.select("frame", "n_hits"), "frame").agg(F.count_if(F.col("state") != F.col("n_hits") % size).alias("wrong"))


@query
def frames_exceptions(spark, sf):
    """Frames of hits with widths far beyond those that the models were fitted on."""
    _, models, _ = framed("EV1", spark, sf)
    h = hits("EV1", spark, sf).withColumn("fall", F.col("fall") + F.when(F.col("event") % 7 == 0, F.lit(1 << 45)).otherwise(0))
    path = scratch(spark, "frames-exceptions")
    FR.write_frames(FR.encode(h, models, CH), path)
    return FR.decode(FR.sound(FR.read_frames(spark, path)), models, CH)


@query
def frames_crc_clean(spark, sf):
    return FR.verify(framed("EV1", spark, sf)[2]).agg(F.count_if(~F.col("ok")).alias("bad"))


@query
def frames_crc_faulty(spark, sf):
    """Of frames with a flipped bit (every third), how many fail; of the others, how many."""
    f = FR.verify(FR.flip_bits(framed("EV1", spark, sf)[2], 3))
    return f.agg(F.count_if((F.col("frame") % 3 == 0) & F.col("ok")).alias("missed"), F.count_if((F.col("frame") % 3 != 0) & ~F.col("ok")).alias("wrongly"))


@query
def frames_fec(spark, sf):
    """Frames of which one bit is turned in Hamming words: repaired, equal to the payload."""
    from hitcodec.operators.fec import hamming_decode, hamming_encode

    def apply(batches):
        for batch in batches:
            good = []
            for x in batch.column(0).to_pylist():
                coded = bytearray(hamming_encode(x))
                if coded:
                    coded[len(coded) // 2] ^= 0x08
                back, _ = hamming_decode(bytes(coded), len(x))
                good.append(back == x)
            yield pa.RecordBatch.from_arrays([pa.array(good, pa.bool_())], ["ok"])

    return framed("EV1", spark, sf)[2].select("width_payload").mapInArrow(apply, "ok boolean").agg(F.count_if(~F.col("ok")).alias("not_repaired"))


@query
def frames_pruned_count(spark, sf):
    _, models, frames = framed("EV1", spark, sf)
    return FR.frames_with_events(frames, models, CH, 10, 20).groupBy("event").agg(F.count(F.lit(1)).alias("n"))


@query
def frames_bin_predicate(spark, sf):
    _, models, frames = framed("EV1", spark, sf)
    return FR.count_at_least(frames, models, "width", 5000)


@query
def frames_realised(spark, sf):
    """Is what frames hold within 3 % of the modelled cost (64 events a frame)."""
    h, models, frames = framed("OR1", spark, sf)
    real = FR.realised_cost(frames).agg(F.sum(F.col("coded_bits") + F.col("raw_bytes") * 8).alias("real"))
    model = C.ladder(h, rungs=("R3",)).where("vtype = 'total'").select((F.col("n_values") * F.col("bits_per_value")).alias("model"))
    return real.crossJoin(model).select((F.abs(F.col("real") / F.col("model") - 1) < 0.03).alias("close"))


named("frames_overheads", lambda spark, sf: (lambda f: FR.overheads(f[2], f[1]).select("frames", "reference_bits", "crc_bits"))(framed("EV1", spark, sf)))


@query
def frames_dump(spark, sf):
    """The readable form of frames: a line for each channel of an event."""
    _, models, frames = framed("EV1", spark, sf)
    r = L.to_channel_records(FR.decode(frames, models, CH))
    line = F.format_string("event %d channel %d: %d pulses from %d", "event", "channel", "pulses", "start")
    return r.select("event", "channel", line.alias("line"))


@query
def unit_merge(spark, sf):
    """Frames of each unit's channels, merged to packets, split and decoded."""
    ship_package(spark)
    h = V.li1(spark, sf, None)
    n = load(spark, sf, "supplier").count() + 1
    units = V.hierarchy(spark, sf)
    models = FR.fit_models(h, n, sparse=True)
    packets = FR.merge_units(FR.encode_by_unit(h, units, models, n))
    return FR.decode(FR.split_units(packets), models, n)


@query
def codec_sizes(spark, sf):
    """Bytes of the archived hits under general codecs, for context; sizes depend on the engine."""
    h = hits("OR1", spark, sf)
    rows = []
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    for codec in ("none", "snappy", "gzip", "zstd"):
        path = scratch(spark, f"codec-{codec}")
        h.write.option("compression", codec).parquet(path)
        p = hadoop.Path(path)
        size = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
        rows.append((codec, int(size)))
    return spark.createDataFrame(rows, "codec string, bytes long")


# --- workloads that no query above covers


@query
def workload_bin_comparison(spark, sf):
    """Simple and adaptive bins of starts and widths side by side, with a comb-shaped and a bell-shaped table."""
    return W.bin_comparison(value_hist("LI1", spark, sf).unionByName(value_hist("EM0", spark, sf)), [12, 16, 20], [16, 64, 256])


@query
def workload_scope_sweep(spark, sf):
    """One table or one for each channel over budgets of bins, in sample and held out (odd events)."""
    return W.scope_sweep(V.em1(spark, sf), [8, 16, 32, 64], F.col("event") % 2 == 1, V.em1(spark, sf).select("channel").distinct().withColumn("class_id", V.div(F.col("channel"), 12).cast("int")))


@query
def workload_archive(spark, sf):
    """Rows that a table and its archive do not share."""
    ship_package(spark)
    h = hits("LI1", spark, sf)
    path = scratch(spark, "archive")
    return W.differences(h, W.restore(spark, path, W.archive(h, path, CH), CH))


@query
def workload_faults(spark, sf):
    f = W.fault_study(framed("LI1", spark, sf)[2], 5)
    return f.select((F.col("damaged") == F.col("detected")).alias("all_detected"), (F.col("damaged") == F.col("repaired")).alias("all_repaired"), (F.col("damaged") > 0).alias("some"))


def _fec(scheme, lost):
    def f(spark, sf):
        frames = framed("EV1", spark, sf)[2]
        back = W.fec_decode(W.fec_encode(frames, scheme), scheme, lost)
        return back.join(frames.select("frame", "width_payload"), "frame").agg(F.count_if(F.col("payload") != F.col("width_payload")).alias("differ"))

    return f


named("fec_hamming", _fec("hamming74", None))
named("fec_parity", _fec("xor_parity", 2))
