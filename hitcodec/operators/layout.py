"""Grouping by channel and relative coding: channel records, value streams, fixed packets and raw words, and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.functions.bits import expgolomb_bits
from hitcodec.sources.views import EPOCH_TICKS, div

TYPES = ("pulses", "start", "width", "distance")


def _placed(hits: DataFrame) -> DataFrame:
    """Each pulse with its event's reference, its place in its channel and the end of the pulse before; one exchange by event."""
    channel = Window.partitionBy("event", "channel").orderBy("rise", "fall")
    return (
        hits.repartition("event")
        .withColumn("ref", F.min("rise").over(Window.partitionBy("event")))
        .withColumn("pos", F.row_number().over(channel) - 1)
        .withColumn("before", F.lag("fall").over(channel))
        .withColumn("pulses", F.count(F.lit(1)).over(Window.partitionBy("event", "channel")))
    )


def value_streams(hits: DataFrame) -> DataFrame:
    """event, channel, pos, vtype, v: the four types as a long table; silent channels are not materialised."""
    value = lambda kind, pos, v: F.struct(pos.cast("int").alias("pos"), F.lit(kind).alias("vtype"), v.cast("long").alias("v"))
    first = F.col("pos") == 0
    each = F.array(
        F.when(first, value("pulses", F.lit(0), F.col("pulses"))),
        F.when(first, value("start", F.lit(0), F.col("rise") - F.col("ref"))),
        value("width", F.col("pos"), F.col("fall") - F.col("rise")),
        F.when(~first, value("distance", F.col("pos") - 1, F.col("rise") - F.col("before"))),
    )
    return _placed(hits).select("event", "channel", F.inline(F.array_compact(each)))


def to_channel_records(hits: DataFrame) -> DataFrame:
    """event, channel, ref, pulses, start, widths, distances: a row for each active channel of an event."""
    p = _placed(hits)
    row = F.struct("pos", (F.col("fall") - F.col("rise")).alias("w"), (F.col("rise") - F.col("before")).alias("d"))
    g = p.groupBy("event", "channel").agg(F.min("ref").alias("ref"), F.min("rise").alias("first"), F.array_sort(F.collect_list(row)).alias("rows"))
    return g.select(
        "event", "channel", "ref", F.size("rows").alias("pulses"), (F.col("first") - F.col("ref")).alias("start"),
        F.transform("rows", lambda r: r["w"]).alias("widths"), F.filter(F.transform("rows", lambda r: r["d"]), lambda d: d.isNotNull()).alias("distances"),
    )


def from_channel_records(records: DataFrame) -> DataFrame:
    """The pulses of channel records, as hits."""
    total = lambda name, j: F.aggregate(F.slice(name, 1, j), F.lit(0).cast("long"), lambda a, x: a + x)
    js = F.sequence(F.lit(0), F.col("pulses") - 1)
    each = F.transform(js, lambda j: F.struct((F.col("ref") + F.col("start") + total("widths", j) + total("distances", j)).alias("rise"), F.element_at("widths", j + 1).alias("w")))
    return records.select("event", "channel", F.inline(each)).select("event", "channel", "rise", (F.col("rise") + F.col("w")).alias("fall"))


def pulse_counts(hits: DataFrame, n_channels: int, n_events: int | None = None) -> DataFrame:
    """v, n: how many channels of all events have v pulses; silent channels by subtraction, never materialised."""
    counts = hits.groupBy("event", "channel").agg(F.count(F.lit(1)).alias("v"))
    some = counts.groupBy("v").agg(F.count(F.lit(1)).alias("n"))
    events = F.lit(n_events) if n_events is not None else F.count_distinct("event")
    zero = counts.agg((events * n_channels - F.count(F.lit(1))).alias("n")).select(F.lit(0).cast("long").alias("v"), "n")
    return some.unionByName(zero)


def pulse_frequencies(hits: DataFrame, n_channels: int, n_events: int | None = None) -> DataFrame:
    """pulses, n, share."""
    counts = pulse_counts(hits, n_channels, n_events)
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select(F.col("v").alias("pulses"), F.col("n").cast("long").alias("n"), F.round(F.col("n") / F.col("total"), 6).alias("share"))


def counts_per_event(hits: DataFrame) -> DataFrame:
    """vtype, n, per_event: mean number of values of the three numeric types in an event."""
    v = value_streams(hits)
    events = hits.agg(F.count_distinct("event").alias("events"))
    g = v.where("vtype <> 'pulses'").groupBy("vtype").agg(F.count(F.lit(1)).alias("n"))
    return g.crossJoin(F.broadcast(events)).select("vtype", "n", F.round(F.col("n") / F.col("events"), 6).alias("per_event"))


def pulse_count_symbols(hits: DataFrame, style: str, n_channels: int) -> DataFrame:
    """Bits that tell the numbers of pulses, for each event: as counts by Exp-Golomb words, as a stop flag after each
    pulse, or as a bitmap of channels and the counts of active ones less one."""
    counts = hits.groupBy("event", "channel").agg(F.count(F.lit(1)).alias("v"))
    g = counts.groupBy("event").agg(F.count(F.lit(1)).alias("active"), F.sum("v").alias("pulses"), F.sum(expgolomb_bits("v")).alias("words"), F.sum(expgolomb_bits(F.col("v") - 1)).alias("less"))
    silent = F.lit(n_channels) - F.col("active")
    bits = {"count": F.col("words") + silent, "flag": F.col("pulses") + n_channels, "bitmap": F.lit(n_channels) + F.col("less")}[style]
    return g.select("event", F.lit(style).alias("style"), bits.cast("long").alias("bits"))


def pack_fixed(hits: DataFrame, n_channels: int, bits: tuple[int, int, int, int] = (4, 28, 27, 28)) -> DataFrame:
    """event, ref, packet: a bit string for each event, channel by channel: pulses, then start, width, (distance, width)...

    Silent channels are their zero count. A value that does not fit its bits is an error. The distance of overlapping
    pulses is negative, by no more than the width before it: it wraps round, and the width tells so (`unpack_fixed`)."""
    column = lambda x: F.col(x) if isinstance(x, str) else x
    wide = lambda x, n: F.raise_error(F.format_string("%d does not fit %d bits", column(x).cast("long"), F.lit(n)))
    field = lambda x, n: F.when(F.shiftright(column(x).cast("long"), n) == 0, F.lpad(F.bin(x), n, "0")).otherwise(wide(x, n))
    r = to_channel_records(hits)
    wrapped = lambda d, w: F.when(d >= 0, F.when(d + w < 1 << bits[3], d).otherwise(wide(d, bits[3]))).when(d >= -w, d + (1 << bits[3])).otherwise(wide(d, bits[3]))
    before = lambda name, j: F.element_at(name, F.greatest(j - 1, F.lit(1)))
    pairs = F.array_join(F.transform(F.sequence(F.lit(1), F.col("pulses")), lambda j: F.concat(F.when(j > 1, field(wrapped(before("distances", j), before("widths", j)), bits[3])).otherwise(""), field(F.element_at("widths", j), bits[2]))), "")
    safe = r.withColumn("distances", F.when(F.size("distances") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.col("distances")))
    own = safe.select("event", "channel", "ref", F.concat(field("pulses", bits[0]), field("start", bits[1]), pairs).alias("word"))
    g = own.groupBy("event").agg(F.min("ref").alias("ref"), F.map_from_entries(F.collect_list(F.struct("channel", "word"))).alias("words"))
    silent = "0" * bits[0]
    packet = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(n_channels - 1)), lambda c: F.coalesce(F.try_element_at("words", c), F.lit(silent))), "")
    return g.select("event", "ref", packet.alias("packet"))


def unpack_fixed(packets: DataFrame, n_channels: int, bits: tuple[int, int, int, int] = (4, 28, 27, 28)) -> DataFrame:
    """The hits of fixed packets: a fold over channels, as the place of each field depends on the counts before it."""
    number = lambda at, n: F.conv(F.substring(F.col("packet"), at, F.lit(n)), 2, 10).cast("long")
    count, pair = F.lit(bits[0]), bits[2] + bits[3]
    state = F.struct(F.lit(1).alias("at"), F.array().cast("array<struct<channel:int,at:int,pulses:int>>").alias("found"))

    def step(acc, channel):
        pulses = number(acc["at"], bits[0]).cast("int")
        size = count + F.when(pulses > 0, F.lit(bits[1] - bits[3]) + pulses * pair).otherwise(0)
        entry = F.array(F.struct(channel.cast("int").alias("channel"), (acc["at"] + count).alias("at"), pulses.alias("pulses")))
        found = F.when(pulses > 0, F.concat(acc["found"], entry)).otherwise(acc["found"])
        return F.struct((acc["at"] + size).alias("at"), found.alias("found"))

    fold = F.aggregate(F.sequence(F.lit(0), F.lit(n_channels - 1)), state, step)
    each = packets.withColumn("f", F.explode(fold["found"])).select("event", "ref", "packet", "f.*")
    at = lambda j: F.col("at") + bits[1] + j * pair  # noqa: E731  where the width of pulse j begins
    js = F.sequence(F.lit(0), F.col("pulses") - 1)
    each = each.withColumn("start", number(F.col("at"), bits[1])).withColumn("widths", F.transform(js, lambda j: number(at(j), bits[2])))
    signed = lambda d, w: F.when(d + w >= 1 << bits[3], d - (1 << bits[3])).otherwise(d)
    distances = F.filter(F.transform(js, lambda j: F.when(j > 0, signed(number(at(j) - bits[3], bits[3]), number(at(j - 1), bits[2])))), lambda d: d.isNotNull())
    return from_channel_records(each.withColumn("distances", distances))


def edges_of(hits: DataFrame) -> DataFrame:
    """Two edges for each pulse."""
    pair = F.array(F.struct(F.col("rise").alias("tick"), F.lit(True).alias("rising")), F.struct(F.col("fall").alias("tick"), F.lit(False).alias("rising")))
    return hits.select("event", "channel", F.inline(pair))


def pack_words(hits: DataFrame) -> DataFrame:
    """event, words: the standard format, 32-bit words in order of time; an epoch word before edges of a new epoch.

    A time word is 0, fine (10 bits), coarse (11), channel (7), rising (1); an epoch word is 1 and 28 bits of epoch. A
    channel or epoch beyond its bits (a tick below 0 too) is an error."""
    fits = F.col("channel").between(0, 127) & F.col("tick").between(0, (EPOCH_TICKS << 28) - 1)
    wide = F.raise_error(F.format_string("channel %d at tick %d does not fit its words", F.col("channel").cast("long"), F.col("tick")))
    e = edges_of(hits).withColumn("tick", F.when(fits, F.col("tick")).otherwise(wide)).withColumn("epoch", div(F.col("tick"), EPOCH_TICKS))
    sub = F.pmod(F.col("tick"), F.lit(EPOCH_TICKS))
    word = (F.pmod(sub, F.lit(500)) * (1 << 21)) + div(sub, 500) * (1 << 10) + F.col("channel") * 8 + F.col("rising").cast("long")
    by = Window.partitionBy("event").orderBy("tick", "channel", "rising")
    new = F.coalesce(F.lag("epoch").over(by) != F.col("epoch"), F.lit(True))
    e = e.withColumn("words", F.when(new, F.array((F.lit(1 << 31) + F.col("epoch")), word)).otherwise(F.array(word))).withColumn("n", F.row_number().over(by))
    g = e.groupBy("event").agg(F.array_sort(F.collect_list(F.struct("n", "words"))).alias("rows"))
    return g.select("event", F.flatten(F.transform("rows", lambda r: r["words"])).alias("words"))


def unpack_words(packets: DataFrame) -> DataFrame:
    """The edges of raw words: event, channel, tick, rising."""
    each = packets.select("event", F.posexplode("words").alias("n", "w"))
    is_epoch = F.col("w") >= (1 << 31)
    epoch = F.last(F.when(is_epoch, F.col("w") - (1 << 31)), ignorenulls=True).over(Window.partitionBy("event").orderBy("n").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    part = lambda shift, bits: F.shiftright("w", shift).bitwiseAND(F.lit((1 << bits) - 1))
    tick = F.col("epoch") * EPOCH_TICKS + part(10, 11) * 500 + part(21, 10)
    return each.withColumn("epoch", epoch).where(~is_epoch).select("event", part(3, 7).cast("int").alias("channel"), tick.alias("tick"), (part(0, 1) == 1).alias("rising"))
