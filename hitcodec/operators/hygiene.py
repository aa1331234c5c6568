"""Edges: which are kept, why others are rejected, and pairs of a rising edge with the falling one that follows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEPT = "kept"


def judge_edges(edges: DataFrame, max_width: int | None = None) -> DataFrame:
    """Adds reason: kept, corrupt, no_fall (a rise not followed by a fall), no_rise, or too_wide; and mate, the other
    edge's tick of a kept or too wide pair. One exchange by event; corrupt edges take no part in the order."""
    by = Window.partitionBy("event", "channel", F.col("rising").isNull()).orderBy("tick", F.col("rising").desc())
    e = edges.withColumns({"_next": F.lead("rising").over(by), "_next_tick": F.lead("tick").over(by), "_prev": F.lag("rising").over(by), "_prev_tick": F.lag("tick").over(by)})
    rising = F.col("rising")
    reason: Column = (
        F.when(rising.isNull(), "corrupt")
        .when(rising & ~F.coalesce("_next", F.lit(True)), KEPT).when(rising, "no_fall")
        .when(F.coalesce("_prev", F.lit(False)), KEPT).otherwise("no_rise")
    )
    mate = F.when(rising, F.col("_next_tick")).otherwise(F.col("_prev_tick"))
    e = e.withColumn("reason", reason).withColumn("mate", F.when(F.col("reason") == KEPT, mate))
    if max_width is not None:
        e = e.withColumn("reason", F.when((F.col("reason") == KEPT) & (F.abs(F.col("mate") - F.col("tick")) > max_width), "too_wide").otherwise(F.col("reason")))
    return e.drop("_next", "_next_tick", "_prev", "_prev_tick")


def filter_edges(edges: DataFrame, max_width: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(kept edges, rejected edges with their reason)."""
    judged = judge_edges(edges, max_width)
    kept = judged.where(F.col("reason") == KEPT).select("event", "channel", "tick", "rising")
    return kept, judged.where(F.col("reason") != KEPT).select("event", "channel", "tick", "rising", "reason")


def pair_edges(edges: DataFrame, max_width: int | None = None) -> DataFrame:
    """Valid pulses of edges, as hits."""
    judged = judge_edges(edges, max_width)
    return judged.where((F.col("reason") == KEPT) & F.col("rising")).select("event", "channel", F.col("tick").alias("rise"), F.col("mate").alias("fall"))


def diagnostics(edges: DataFrame, max_width: int | None = None) -> DataFrame:
    """Reject counts and rate for each channel."""
    bad = (F.col("reason") != KEPT).cast("long")
    return judge_edges(edges, max_width).groupBy("channel").agg(F.count(F.lit(1)).alias("edges"), F.sum(bad).alias("rejected"), F.round(F.avg(bad), 6).alias("rate"))


def exception_words(rejected: DataFrame, word_bits: int = 32) -> DataFrame:
    """Rejected edges kept in the standard word format at the end of their event: words and bits for each event."""
    return rejected.groupBy("event").agg(F.count(F.lit(1)).alias("words"), (F.count(F.lit(1)) * word_bits).alias("bits"))


def encode_mode(edges: DataFrame, mode: str = "main") -> DataFrame:
    """What a run keeps for each event: every measured edge as a word (diagnostic), or only filtered edges (main)."""
    if mode == "diagnostic":
        return edges.groupBy("event").agg(F.count(F.lit(1)).alias("edges"))
    if mode == "main":
        return filter_edges(edges)[0].groupBy("event").agg(F.count(F.lit(1)).alias("edges"))
    raise ValueError(f"no such mode: {mode}")
