"""Canonical views: the given tables as detector times, symbols and values, by integer arithmetic only.

hits: event, channel, rise, fall. edges: event, channel, tick, rising (null: a corrupt measurement).
values: event, channel, v. symbols: frame, pos, sym.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hitcodec.session import ship_package
from hitcodec.sources.tables import load

CHANNELS = 48
EPOCH_TICKS = 1_024_000  # 500 fine times 2048 coarse steps
P = 1_000_003
# The printed frequencies of 0..8 pulses, accumulated and scaled to a million.
PULSE_STEPS = (882500, 948410, 967890, 977265, 992295, 998825, 999835, 999965, 999967)
START_2024 = 1_704_067_200_000_000


def div(a: Column, b: Column | int) -> Column:
    """Integer division."""
    return F.call_function("div", a.cast("long"), (F.lit(b) if isinstance(b, int) else b).cast("long"))


def cents(c: Column | str) -> Column:
    return F.round((F.col(c) if isinstance(c, str) else c) * 100).cast("long")


def micros(c: Column | str) -> Column:
    return F.unix_micros((F.col(c) if isinstance(c, str) else c).cast("timestamp"))


def mix(e: Column) -> Column:
    """The fifth power modulo a prime: a permutation, every product below 2**63."""
    x = F.pmod(e, F.lit(P))
    s = (x * x) % P
    return (((s * s) % P) * x) % P


def ev1(spark: SparkSession, sf_dir: str) -> DataFrame:
    rise = micros("ts") - START_2024
    return load(spark, sf_dir, "events").select(div(F.col("event_id"), 24).alias("event"), (F.col("user_id") % CHANNELS).cast("int").alias("channel"), rise.alias("rise"), (rise + cents("value")).alias("fall"))


def ev2(spark: SparkSession, sf_dir: str) -> DataFrame:
    kind = F.col("event_type")
    rising = F.when(kind.isin("view", "click"), True).when(kind.isin("signup", "purchase"), False)
    return load(spark, sf_dir, "events").select(div(F.col("event_id"), 336).alias("event"), (F.col("user_id") % CHANNELS).cast("int").alias("channel"), (micros("ts") - START_2024).alias("tick"), rising.alias("rising"))


def li1(spark: SparkSession, sf_dir: str, channels: int | None = CHANNELS) -> DataFrame:
    """With channels=None the supplier is the channel (LI3's hits)."""
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("long")
    rise = cents("l_extendedprice") % EPOCH_TICKS + days * EPOCH_TICKS
    width = (F.col("l_quantity") * 100).cast("long") + F.round(F.col("l_discount") * 100).cast("long")
    channel = F.col("l_suppkey") % channels if channels else F.col("l_suppkey")
    return load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("event"), channel.cast("int").alias("channel"), rise.alias("rise"), (rise + width).alias("fall"))


def li2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("event"), F.col("l_quantity").cast("int").alias("channel"), cents("l_extendedprice").alias("v"))


def hierarchy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """channel (supplier), class_id (nation), unit_id (region)."""
    s, n = load(spark, sf_dir, "supplier"), load(spark, sf_dir, "nation")
    return s.join(n, s.s_nationkey == n.n_nationkey).select(F.col("s_suppkey").cast("int").alias("channel"), F.col("s_nationkey").alias("class_id"), F.col("n_regionkey").alias("unit_id"))


def or0(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event, channel, id, pulses for every order and channel, zeros included."""
    return draws(load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("event")))


def draws(events: DataFrame) -> DataFrame:
    """Adds channel, id, pulses: a row for each event and channel; further columns of the events are kept at the end."""
    more = [c for c in events.columns if c != "event"]
    each = events.select("*", F.explode(F.sequence(F.lit(0), F.lit(CHANNELS - 1))).alias("channel"))
    each = each.withColumn("id", F.col("event") * CHANNELS + F.col("channel"))
    # behind a generator, as a filter on the pulses would else compute the draw again for each step
    each = each.select("*", F.explode(F.array(mix(F.col("id") * 7919 + 104729))).alias("u"))
    pulses = F.lit(0)
    for k, step in reversed(list(enumerate(PULSE_STEPS))):
        pulses = F.when(F.col("u") < step, k).otherwise(pulses)
    return each.select("event", "channel", "id", pulses.alias("pulses"), *more)


def or1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pulses of the active channels, some thousand orders at a time in Arrow batches: integer arithmetic of whole columns."""
    ship_package(spark)
    n_channels, prime, steps = CHANNELS, P, np.array(PULSE_STEPS)
    rows = 2048

    def apply(batches):
        def mixed(e):
            x = e % prime  # as pmod: above 0
            s = x * x % prime
            return s * s % prime * x % prime

        for batch in batches:
            for begin in range(0, batch.num_rows, rows):
                column = batch.column(0).slice(begin, rows)
                orders = column.filter(column.is_valid()).to_numpy(zero_copy_only=False)
                key = (orders[:, None] * n_channels + np.arange(n_channels)).ravel()
                pulses = np.searchsorted(steps, mixed(key * 7919 + 104729), "right")
                active = np.flatnonzero((pulses > 0) & (pulses < len(steps)))
                n, key = pulses[active], key[active]
                ends = np.cumsum(n)
                first = np.repeat(ends - n, n)
                channel = np.repeat(active % n_channels, n)
                k = np.repeat(key, n) * 16 + np.arange(len(first)) - first
                width = 2000 + channel * 30 + sum(mixed(k * m + a) % 1000 for m, a in ((7907, 7), (7901, 11), (7883, 13), (7879, 17)))
                start = mixed(key * 611953 + 31)
                dist = 500 + mixed(k * 7877 + 19) ** 3 // 100_000_000_000
                before = np.concatenate([[0], np.cumsum(width + dist)])  # of all pulses before, less those of other channels
                rise = np.repeat(start**3 // 10_000_000_000, n) + before[:-1] - before[first]
                event = np.repeat(orders[active // n_channels], n)
                yield pa.RecordBatch.from_arrays([pa.array(event, pa.int64()), pa.array(channel, pa.int32()), pa.array(rise, pa.int64()), pa.array(rise + width, pa.int64())], ["event", "channel", "rise", "fall"])

    return load(spark, sf_dir, "orders").select("o_orderkey").mapInArrow(apply, "event long, channel int, rise long, fall long")


def em0(spark: SparkSession, sf_dir: str) -> DataFrame:
    each = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("event"), F.posexplode("embedding").alias("channel", "e"))
    return each.select("event", "channel", F.round((F.col("e").cast("double") + 1) * 1048576).cast("long").alias("v"))


def em1(spark: SparkSession, sf_dir: str) -> DataFrame:
    each = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("event"), F.posexplode("embedding").alias("channel", "e")).where(f"channel < {CHANNELS}")
    return each.select("event", "channel", (F.col("channel") * 90 + 20000 + F.round(F.col("e").cast("double") * 8000).cast("long")).alias("v"))


def cv1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The role is the channel: its rank by name."""
    c = load(spark, sf_dir, "conversations").where("role is not null")
    ranks = c.select("role").distinct().withColumn("channel", (F.dense_rank().over(Window.orderBy("role")) - 1).cast("int"))  # a row for each role
    return c.join(ranks, "role").select(F.col("conv_id").alias("event"), "channel", F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("v"))


def characters(df: DataFrame, frame: str, text: str) -> DataFrame:
    """Code points of a text column; 256 stands for all above 255. A row for each frame: frame, syms."""
    points = F.transform(F.split(F.coalesce(F.col(text), F.lit("")), ""), F.ascii)
    syms = F.transform(F.filter(points, lambda p: p > 0), lambda p: F.least(p, F.lit(256)))
    return df.select(F.col(frame).cast("long").alias("frame"), syms.alias("syms"))


def do1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return characters(load(spark, sf_dir, "documents"), "doc_id", "text")


def bm1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return characters(load(spark, sf_dir, "benchmark"), "item_id", "text")


def pg1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return characters(load(spark, sf_dir, "pages"), "page_id", "html")


def lb1(spark: SparkSession, sf_dir: str, column: str = "toxic", frame: int = 1024) -> DataFrame:
    """Binary symbols in doc_id order: frame (of doc_ids), pos, sym."""
    return load(spark, sf_dir, "labels").where(f"{column} is not null").select(div(F.col("doc_id"), frame).alias("frame"), F.col("doc_id").alias("pos"), F.col(column).alias("sym"))


def cu1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """OR0 with the market segment of the order's customer as event class."""
    o, c = load(spark, sf_dir, "orders"), load(spark, sf_dir, "customer")
    # merged before the channels are made: orders and customers grow, and compressed files hide how much
    kind = o.join(c.hint("merge"), o.o_custkey == c.c_custkey).select(F.col("o_orderkey").alias("event"), F.col("c_mktsegment").alias("event_class"))
    return draws(o.select(F.col("o_orderkey").alias("event")).join(kind.hint("merge"), "event"))


HITS = {"EV1": ev1, "LI1": li1, "OR1": or1}
