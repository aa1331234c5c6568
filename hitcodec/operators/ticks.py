"""Times: split and flat ticks, and reference times of events."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.sources.views import div

FINE, COARSE = 500, 2048


def split_tick(df: DataFrame, col: str = "tick") -> DataFrame:
    """Adds fine (0..499), coarse (0..2047) and epoch."""
    step = F.col(col) - F.pmod(F.col(col), F.lit(FINE))
    steps = div(step, FINE)
    return df.withColumns({"fine": F.pmod(F.col(col), F.lit(FINE)).cast("int"), "coarse": F.pmod(steps, F.lit(COARSE)).cast("int"), "epoch": div(steps - F.pmod(steps, F.lit(COARSE)), COARSE)})


def join_tick(df: DataFrame, to: str = "tick") -> DataFrame:
    """The flat tick of the three fields."""
    return df.withColumn(to, F.col("fine") + (F.col("coarse") + F.col("epoch") * COARSE) * FINE)


def with_reference(df: DataFrame, mode: str = "min", col: str = "rise", ref_channel: int = 0) -> DataFrame:
    """Adds ref: the event's least time, the least of one channel (null without it), or zero for mode "none"."""
    event = Window.partitionBy("event")
    if mode == "min":
        return df.withColumn("ref", F.min(col).over(event))
    if mode == "channel":
        return df.withColumn("ref", F.min(F.when(F.col("channel") == ref_channel, F.col(col))).over(event))
    if mode == "none":
        return df.withColumn("ref", F.lit(0).cast("long"))
    raise ValueError(f"no such reference: {mode}")


def quantise_reference(df: DataFrame, drop_bits: int) -> DataFrame:
    """The reference with its low bits dropped."""
    return df.withColumn("ref", F.shiftleft(F.shiftright("ref", drop_bits), drop_bits))
