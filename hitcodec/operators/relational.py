"""Relational operators a user of the methods needs around them: joins, aggregates, windows, sets and functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.functions.bits import bit_length


BROADCAST_ROWS = 1_000_000  # of a table that the driver collects and each executor holds: some ten MB of slim rows


def join_with(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None) -> DataFrame:
    """A join with a strategy hint: broadcast, merge or shuffle_hash.

    A table of more than BROADCAST_ROWS rows, counted, is merged instead of broadcast: the same rows, however many."""
    if strategy == "broadcast" and right.count() > BROADCAST_ROWS:
        strategy = "merge"
    return left.join(right.hint(strategy) if strategy else right, on, how)


def join_asof(left: DataFrame, right: DataFrame, on: str, by: list[str], columns: list[str]) -> DataFrame:
    """Each left row with the columns of the last right row of its group whose `on` is not later; one shuffle, no pairs.

    Both sides are put in one order, right rows before left ones at the same time, and the last right row is carried."""
    carried = F.struct(*columns)
    a = left.select(*by, F.col(on).alias("_t"), F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.select(carried.alias("x")).schema["x"].dataType).alias("_r"))
    b = right.select(*by, F.col(on).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), carried.alias("_r"))
    w = Window.partitionBy(*by).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = a.unionByName(b).withColumn("_found", F.last("_r", ignorenulls=True).over(w)).where("_side = 1")
    return both.select("_row.*", *[F.col(f"_found.{c}").alias(f"last_{c}") for c in columns])


def join_interval(h: DataFrame, cell: int) -> DataFrame:
    """event, a, b, overlap: pairs of channels with overlapping pulses in an event, by cells of time.

    A pulse's class is the power of two above its length (`cell`, a power of two, at least), so that it lies in one or two
    cells of its class, however long it is. It is asked for in the cells of all longer classes that occur; a pair meets in
    the cells of the longer one's class, and counts in the one where the later pulse begins, hence once."""
    bits = cell.bit_length() - 1
    p = h.withColumn("kind", F.greatest(F.lit(bits), bit_length(F.col("fall") - F.col("rise"))).cast("int"))
    top = p.agg(F.max("kind").alias("top"))  # one row
    cells = lambda k: F.explode(F.expr(f"sequence(shiftright(rise, {k}), shiftright(fall, {k}))")).alias("cell")
    left = p.select("event", F.col("kind").alias("at"), F.col("channel").alias("x"), F.col("rise").alias("rx"), F.col("fall").alias("fx"), cells("kind"))
    asked = p.crossJoin(F.broadcast(top)).select("event", "channel", "rise", "fall", "kind", F.explode(F.sequence("kind", "top")).alias("at"))
    right = asked.select("event", "at", "kind", F.col("channel").alias("y"), F.col("rise").alias("ry"), F.col("fall").alias("fy"), cells("at"))
    start, end = F.greatest("rx", "ry"), F.least("fx", "fy")
    once = (F.col("kind") < F.col("at")) & (F.col("x") != F.col("y")) | (F.col("kind") == F.col("at")) & (F.col("x") < F.col("y"))
    # merged: sizes estimated before the explosions are far too small for a broadcast
    both = left.join(right.hint("merge"), ["event", "at", "cell"]).where(once & (start < end) & (F.col("cell") == F.expr("shiftright(greatest(rx, ry), at)")))
    first = F.col("x") < F.col("y")
    pick = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
    return both.select("event", pick("x", "y").alias("a"), pick("y", "x").alias("b"), pick("rx", "ry").alias("ra"), pick("ry", "rx").alias("rb"), (end - start).alias("overlap"))


def topk_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= k)


def salted_count(df: DataFrame, keys: list[str], salts: int = 32) -> DataFrame:
    """Counts by key in two steps, for aggregates whose partial step can't reduce a hot key."""
    first = df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(*keys, "_salt").agg(F.count(F.lit(1)).alias("_n"))
    return first.groupBy(*keys).agg(F.sum("_n").alias("n"))
