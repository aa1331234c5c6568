"""Histograms, entropies and empirical distributions. Values are first counted per distinct value, with map-side sums."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def histogram(values: DataFrame, keys: list[str], v: str = "v") -> DataFrame:
    """keys, v, n."""
    return values.groupBy(*keys, F.col(v).alias("v")).agg(F.count(F.lit(1)).alias("n"))


def cumulative(hist: DataFrame, keys: list[str]) -> DataFrame:
    """Adds cum (values up to v) and total. Sums run inside coarse ranges of v, then over the ranges, so that the values of
    one key spread over many tasks."""
    range_of = F.shiftright("v", 12)
    h = hist.withColumn("_r", range_of)
    inside = Window.partitionBy(*keys, "_r").orderBy("v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    across = Window.partitionBy(*keys).orderBy("_r").rowsBetween(Window.unboundedPreceding, -1)
    ranges = h.groupBy(*keys, "_r").agg(F.sum("n").alias("_n"))
    ranges = ranges.withColumn("_before", F.coalesce(F.sum("_n").over(across), F.lit(0))).withColumn("total", F.sum("_n").over(Window.partitionBy(*keys))).drop("_n")
    return h.withColumn("_cum", F.sum("n").over(inside)).join(ranges, [*keys, "_r"]).withColumn("cum", F.col("_before") + F.col("_cum")).drop("_cum", "_before", "_r")


def entropy(hist: DataFrame, keys: list[str], n: str = "n") -> DataFrame:
    """keys, total, symbols, entropy: bits a value; by log2 N - sum(n log2 n) / N, one pass."""
    total, some = F.sum(n), F.sum(F.col(n) * F.log2(n))
    return hist.groupBy(*keys).agg(total.alias("total"), F.count(F.lit(1)).alias("symbols"), F.greatest(F.lit(0.0), F.log2(total) - some / total).alias("entropy"))


def information(p: Column) -> Column:
    """Bits of an event of probability p."""
    return -F.log2(p)


def ecdf(values: DataFrame, points: int = 101, key: str = "vtype") -> DataFrame:
    """key, i (rank), v, share: the values at evenly spaced ranks of each key, exact, from the cumulative histogram."""
    c = cumulative(histogram(values, [key]), [key])
    steps = F.sequence(F.lit(0), F.lit(points - 1))
    rank = lambda k: F.greatest(F.lit(1), F.call_function("div", k * F.col("total"), F.lit(points - 1).cast("long")))
    ranks = F.array_distinct(F.transform(steps, lambda k: rank(k.cast("long"))))
    held = F.filter(ranks, lambda r: (r > F.col("cum") - F.col("n")) & (r <= F.col("cum")))
    return c.withColumn("i", F.explode(held)).select(key, F.col("i").cast("long").alias("i"), "v", F.round(F.col("i") / F.col("total"), 6).alias("share"))


def mutual_information(hits: DataFrame, n_events: int) -> DataFrame:
    """ch1, ch2, both, mi: of the activity of channel pairs that are ever active together; an equi-join on the event."""
    active = hits.select("event", "channel").distinct()
    one = active.groupBy("channel").agg(F.count(F.lit(1)).alias("n"))
    a, b = active.select("event", F.col("channel").alias("ch1")), active.select("event", F.col("channel").alias("ch2"))
    pairs = a.join(b, "event").where("ch1 < ch2").groupBy("ch1", "ch2").agg(F.count(F.lit(1)).alias("both"))
    pairs = pairs.join(one.select(F.col("channel").alias("ch1"), F.col("n").alias("n1")), "ch1").join(one.select(F.col("channel").alias("ch2"), F.col("n").alias("n2")), "ch2")
    total = F.lit(float(n_events))

    def term(joint: Column, left: Column, right: Column) -> Column:
        return F.when(joint > 0, joint / total * F.log2(joint * total / (left * right))).otherwise(0.0)

    n1, n2, k = F.col("n1"), F.col("n2"), F.col("both")
    mi = term(k, n1, n2) + term(n1 - k, n1, total - n2) + term(n2 - k, total - n1, n2) + term(total - n1 - n2 + k, total - n1, total - n2)
    return pairs.select("ch1", "ch2", "both", F.round(mi, 6).alias("mi"))


def delta_code(df: DataFrame, value: str, by: list[str], order: list[str], rounds: int = 1) -> DataFrame:
    """Adds delta: the value less the one before it in its group (the first as it is); repeated `rounds` times."""
    w = Window.partitionBy(*by).orderBy(*order)
    df = df.withColumn("delta", F.col(value))
    for _ in range(rounds):
        df = df.withColumn("_before", F.lag("delta").over(w)).withColumn("delta", F.col("delta") - F.coalesce("_before", F.lit(0))).drop("_before")
    return df


def delta_decode(df: DataFrame, by: list[str], order: list[str], to: str = "value") -> DataFrame:
    """The values of first-order differences."""
    w = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return df.withColumn(to, F.sum("delta").over(w))
