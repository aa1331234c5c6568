"""Cost measures: the rungs from raw words to separate models, in bits an event, by value type and in all.

Rungs: R0 raw words, R1 fixed-length relative values, R1b Exp-Golomb, R2 Huffman with the top eight bits, R3 adaptive bins
with an accurate coder, R4 the same for each channel. Every rung is one pass over a shared histogram or a window.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.functions.bits import bit_length, expgolomb_bits, radix_block
from hitcodec.operators.bins import adaptive_bins, simple_huffman
from hitcodec.operators.histo import entropy
from hitcodec.operators.layout import edges_of, value_streams
from hitcodec.sources.views import EPOCH_TICKS, div

RUNGS = ("R0", "R1", "R1b", "R2", "R3", "R4")
LADDER = ["rung", "vtype", "n_values", "n_bins", "bits_per_value", "bits_per_event"]


def cost_raw_words(hits: DataFrame) -> DataFrame:
    """events, words, epoch_words: 32 bits an edge and a change of epoch; the first edge of an event is a change."""
    e = edges_of(hits).withColumn("epoch", div(F.col("tick"), EPOCH_TICKS))
    by = Window.partitionBy("event").orderBy("tick", "channel", "rising")
    new = F.coalesce(F.lag("epoch").over(by) != F.col("epoch"), F.lit(True)).cast("long")
    return e.select("event", new.alias("new")).agg(F.count_distinct("event").alias("events"), F.count(F.lit(1)).alias("words"), F.sum("new").alias("epoch_words"))


def counted(hits: DataFrame, n_channels: int, by_channel: bool = False) -> DataFrame:
    """(channel,) vtype, v, n with the silent channels' zeros among the pulses."""
    keys = ["channel", "vtype"] if by_channel else ["vtype"]
    return _with_silent(value_streams(hits).groupBy(*keys, "v").agg(F.count(F.lit(1)).alias("n")), hits, n_channels, by_channel)


def _with_silent(h: DataFrame, hits: DataFrame, n_channels: int, by_channel: bool) -> DataFrame:
    keys = ["channel", "vtype"] if by_channel else ["vtype"]
    events = hits.agg(F.count_distinct("event").alias("events"))
    active = h.where("vtype = 'pulses'").groupBy(*keys).agg(F.sum("n").alias("a")).crossJoin(F.broadcast(events))
    size = F.col("events") if by_channel else F.col("events") * n_channels
    zero = active.select(*keys, F.lit(0).cast("long").alias("v"), (size - F.col("a")).alias("n")).where("n > 0")
    return h.unionByName(zero)


def cost_fixed(hist: DataFrame) -> DataFrame:
    """vtype, n_values, bits: every value in the bits of its type's greatest."""
    return hist.groupBy("vtype").agg(F.sum("n").alias("n_values"), (F.sum("n") * bit_length(F.max("v"))).alias("bits"))


def cost_expgolomb(hist: DataFrame) -> DataFrame:
    return hist.groupBy("vtype").agg(F.sum("n").alias("n_values"), F.sum(F.col("n") * expgolomb_bits("v")).alias("bits"))


def cost_unary(hist: DataFrame) -> DataFrame:
    return hist.groupBy("vtype").agg(F.sum("n").alias("n_values"), F.sum(F.col("n") * (F.col("v") + 1)).alias("bits"))


def cost_radix(hist: DataFrame, m: int) -> DataFrame:
    """Blocks of as many digits of base m as fit 63 bits, each in the bits of the block's greatest number."""
    digits = radix_block(m)
    bits = (m**digits - 1).bit_length()
    return hist.groupBy("vtype").agg(F.sum("n").alias("n_values"), (F.sum("n") * (bits / digits)).alias("bits"))


def cost_entropy(hist: DataFrame) -> DataFrame:
    """vtype, n_values, symbols, bits a value: the limit for coders of independent values."""
    e = entropy(hist, ["vtype"])
    return e.select("vtype", F.col("total").cast("long").alias("n_values"), "symbols", F.round("entropy", 4).alias("bits_per_value"))


def _adaptive(hist: DataFrame, keys: list[str], share: int) -> DataFrame:
    """vtype, n_values, n_bins, bits of adaptive bins (numeric types) and plain symbols (pulses)."""
    bins = adaptive_bins(hist.where("vtype <> 'pulses'"), keys, share=share).where("n > 0")
    raw = bins.select(*keys, "n", F.col("bin_width").cast("long").alias("w"))
    both = raw.unionByName(hist.where("vtype = 'pulses'").select(*keys, F.col("n").cast("long").alias("n"), F.lit(0).cast("long").alias("w")))
    g = both.groupBy(*keys).agg(F.sum("n").alias("n_values"), F.count(F.lit(1)).alias("n_bins"), (F.sum("n") * F.log2(F.sum("n")) - F.sum(F.col("n") * F.log2("n")) + F.sum(F.col("n") * F.col("w"))).alias("bits"))
    return g.groupBy("vtype").agg(F.sum("n_values").alias("n_values"), F.sum("n_bins").alias("n_bins"), F.sum("bits").alias("bits"))


def ladder(hits: DataFrame, n_channels: int = 48, rungs: tuple = RUNGS, share: int = 256, channel_share: int = 32) -> DataFrame:
    """rung, vtype (or total), n_values, n_bins, bits_per_value, bits_per_event."""
    parts: list[DataFrame] = []
    none = F.lit(None).cast("long")
    if "R0" in rungs:
        w = cost_raw_words(hits).select("events", F.inline(F.array(F.struct(F.lit("time_words").alias("vtype"), F.col("words").alias("n_values")), F.struct(F.lit("epoch_words").alias("vtype"), F.col("epoch_words").alias("n_values")))))
        parts.append(w.select(F.lit("R0").alias("rung"), "vtype", "n_values", none.alias("n_bins"), (F.col("n_values") * 32.0).alias("bits")))
    # one histogram by channel; the global one is its sum
    own = value_streams(hits).groupBy("channel", "vtype", "v").agg(F.count(F.lit(1)).alias("n"))
    hist = _with_silent(own.groupBy("vtype", "v").agg(F.sum("n").alias("n")), hits, n_channels, False) if "R4" in rungs else counted(hits, n_channels)
    for rung, cost in (("R1", cost_fixed), ("R1b", cost_expgolomb)):
        if rung in rungs:
            parts.append(cost(hist).select(F.lit(rung).alias("rung"), "vtype", "n_values", none.alias("n_bins"), F.col("bits").cast("double").alias("bits")))
    if "R2" in rungs:
        s = simple_huffman(hist, ["vtype"])
        parts.append(s.select(F.lit("R2").alias("rung"), "vtype", "n_values", "n_bins", (F.col("coded_bits") + F.col("low_bits") * F.col("n_values")).cast("double").alias("bits")))
    if "R3" in rungs:
        parts.append(_adaptive(hist, ["vtype"], share).select(F.lit("R3").alias("rung"), "vtype", "n_values", "n_bins", "bits"))
    if "R4" in rungs:
        parts.append(_adaptive(_with_silent(own, hits, n_channels, True), ["channel", "vtype"], channel_share).select(F.lit("R4").alias("rung"), "vtype", "n_values", "n_bins", "bits"))
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    events = F.broadcast(hits.agg(F.count_distinct("event").alias("events")))
    g = every.rollup("rung", "vtype").agg(F.sum("n_values").alias("n_values"), F.sum("n_bins").alias("n_bins"), F.sum("bits").alias("bits")).where("rung is not null")
    return g.crossJoin(events).select(
        "rung", F.coalesce("vtype", F.lit("total")).alias("vtype"), F.col("n_values").cast("long").alias("n_values"), F.col("n_bins").cast("long").alias("n_bins"),
        F.round(F.col("bits") / F.col("n_values"), 3).alias("bits_per_value"), F.round(F.col("bits") / F.col("events"), 3).alias("bits_per_event"),
    )


def with_ratio(steps: DataFrame) -> DataFrame:
    """The totals with their ratio to the first rung and the gain on the one before."""
    t = steps.where("vtype = 'total'")
    first = F.broadcast(t.where("rung = 'R0'").select(F.col("bits_per_event").alias("_raw")))
    by = Window.orderBy("rung")  # six rows
    t = t.crossJoin(first)
    return t.select("rung", "bits_per_event", F.round(F.col("bits_per_event") / F.col("_raw"), 4).alias("ratio"), F.round(1 - F.col("bits_per_event") / F.lag("bits_per_event").over(by), 4).alias("gain"))
