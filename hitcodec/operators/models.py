"""Model scopes (one table, per channel, class or unit), what tables cost, hold-out cost, zero-start pointers, classes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from hitcodec.operators.bins import _changes, _streamed_bins, adaptive_bins, bin_cost
from hitcodec.operators.histo import entropy, histogram


def scope_values(values: DataFrame, scope: str, classes: DataFrame | None = None) -> DataFrame:
    """Adds scope_id: 0 (global), the channel, or the class_id or unit_id that a map of channels gives."""
    if scope == "global":
        return values.withColumn("scope_id", F.lit(0))
    if scope == "channel":
        return values.withColumn("scope_id", F.col("channel").cast("int"))
    if scope in ("class", "unit"):
        column = f"{scope}_id"
        return values.join(classes.select("channel", F.col(column).cast("int").alias("scope_id")), "channel")
    if scope == "event_class":
        return values.join(classes.select("event", F.col("event_class").alias("scope_id")), "event")
    raise ValueError(f"no such scope: {scope}")


def scope_cost(values: DataFrame, scope: str, share: int, classes: DataFrame | None = None) -> DataFrame:
    """scope, models, n_bins, bits a value, table_bits of adaptive bins fitted for each scope_id."""
    hist = histogram(scope_values(values, scope, classes), ["scope_id"])
    c = bin_cost(adaptive_bins(hist, ["scope_id"], share=share), ["scope_id"])
    g = c.agg(F.count(F.lit(1)).alias("models"), F.sum("n_bins").alias("n_bins"), F.sum("n_values").alias("n_values"), F.sum(F.col("n_values") * F.col("total")).alias("bits"))
    return g.select(F.lit(scope).alias("scope"), "models", "n_bins", F.round(F.col("bits") / F.col("n_values"), 3).alias("bits_per_value"), model_bits("n_bins").alias("table_bits"))


def model_bits(n_bins: str, start_bits: int = 32, width_bits: int = 6, count_bits: int = 16):
    """Bits to send a bin table with its counts."""
    return (F.col(n_bins) * (start_bits + width_bits + count_bits)).cast("long")


def scope_comparison(values: DataFrame, scopes: list[str], share: int, classes: DataFrame | None = None) -> DataFrame:
    out = None
    for scope in scopes:
        one = scope_cost(values, scope, share, classes)
        out = one if out is None else out.unionByName(one)
    return out


def break_even(comparison: DataFrame) -> DataFrame:
    """scope, saved (bits a value against one table), values_to_repay the larger table."""
    one = comparison.where("scope = 'global'").select(F.col("bits_per_value").alias("_b"), F.col("table_bits").alias("_t"))
    both = comparison.crossJoin(F.broadcast(one)).withColumn("saved", F.round(F.col("_b") - F.col("bits_per_value"), 3))
    repay = F.when(F.col("saved") > 0, F.ceil((F.col("table_bits") - F.col("_t")) / F.col("saved")))
    return both.select("scope", "models", "bits_per_value", "table_bits", "saved", repay.cast("long").alias("values_to_repay"))


def cluster_channels(values: DataFrame, k: int, cell_bits: int = 8) -> DataFrame:
    """channel, class_id: channels merged greedily, each time the pair whose joint histogram costs least more.

    The driver holds one coarse histogram for each channel."""
    h = values.groupBy("channel", F.shiftright("v", cell_bits).alias("b")).agg(F.count(F.lit(1)).alias("n")).toPandas()
    table = h.pivot(index="channel", columns="b", values="n").fillna(0.0)
    rows = [np.asarray(x, np.float64) for x in table.to_numpy()]
    members = [[int(c)] for c in table.index]

    def bits(x: np.ndarray) -> float:
        x = x[x > 0]
        return float(x.sum() * np.log2(x.sum()) - (x * np.log2(x)).sum())

    costs = [bits(x) for x in rows]
    joint = {(i, j): bits(rows[i] + rows[j]) - costs[i] - costs[j] for i in range(len(rows)) for j in range(i)}
    live = set(range(len(rows)))
    while len(live) > k:
        i, j = min((p for p in joint if p[0] in live and p[1] in live), key=lambda p: (joint[p], p))
        rows[j], members[j] = rows[j] + rows[i], members[j] + members[i]
        costs[j] = bits(rows[j])
        live.discard(i)
        for x in live - {j}:
            joint[max(x, j), min(x, j)] = bits(rows[x] + rows[j]) - costs[x] - costs[j]
    found = [(c, n) for n, i in enumerate(sorted(live)) for c in members[i]]
    return values.sparkSession.createDataFrame(found, "channel int, class_id int")


def cross_entropy(model: DataFrame, hist: DataFrame, keys: list[str]) -> DataFrame:
    """keys, n, bits a value of data coded by a model of other data (v, n each; one is added to each of its counts)."""
    total = model.groupBy(*keys).agg(F.sum("n").alias("_total"), F.count(F.lit(1)).alias("_m"))
    m = model.select(*keys, "v", F.col("n").alias("_n"))
    both = hist.join(m, [*keys, "v"], "left").join(total, keys)
    p = (F.coalesce("_n", F.lit(0)) + 1) / (F.col("_total") + F.col("_m") + 1)
    return both.groupBy(*keys).agg(F.sum("n").cast("long").alias("n"), F.round(F.sum(-F.col("n") * F.log2(p)) / F.sum("n"), 4).alias("bits"))


def held_costs(hist: DataFrame, keys: list[str], shares: list[int]) -> DataFrame:
    """keys, share, n_bins, test, n, bits: of adaptive bins fitted on the rows whose `test` is false, on both parts.

    hist: keys, test, v, n. Bins are fitted in streams and travel in closures (some hundred a group and share); values
    outside them cost 64 bits. Groups without rows to fit on have one bin, and no bits."""
    fits = hist.where(~F.col("test")).withColumn("share", F.lit([int(x) for x in shares]))
    found: dict[tuple, dict[int, list]] = {}
    for r in _streamed_bins(fits, keys).orderBy("share", "bin_start").collect():
        found.setdefault(tuple(r[k] for k in keys), {}).setdefault(r["share"], []).append((r["bin_start"], r["bin_width"], r["n"]))
    tables = {}
    for key, by_share in found.items():
        for share, bins in by_share.items():
            n = np.array([b[2] + 1 for b in bins], np.float64)
            tables[key, share] = np.array([b[0] for b in bins]), np.array([b[1] for b in bins]), np.log2(n / n.sum())
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in hist.schema.fields if f.name in keys)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            cuts = [0, *_changes(batch.select([*keys, "test"]).to_struct_array()), batch.num_rows]
            v, n = (batch.column(len(keys) + k).to_numpy() for k in (1, 2))
            for a, z in zip(cuts, cuts[1:]):
                key = tuple(batch.column(k)[a].as_py() for k in range(len(keys)))
                for share in shares:
                    bits, n_bins = 0.0, 1
                    if (key, share) in tables:
                        starts, widths, logs = tables[key, share]
                        at = np.maximum(np.searchsorted(starts, v[a:z], "right") - 1, 0)
                        inside = (v[a:z] >= starts[0]) & (v[a:z] < starts[-1] + (1 << int(widths[-1])))
                        bits, n_bins = float((np.where(inside, widths[at] - logs[at], 64.0) * n[a:z]).sum()), len(starts)
                    rows.append((*key, share, n_bins, batch.column(len(keys))[a].as_py(), int(n[a:z].sum()), bits))
            names = [*keys, "share", "n_bins", "test", "n", "bits"]
            yield pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows], schema)

    made = StructType.fromDDL(f"{kinds}, share int, n_bins long, test boolean, n long, bits double")
    schema = to_arrow_schema(made)
    ordered = hist.select(*keys, "test", "v", F.col("n").cast("long").alias("n")).sortWithinPartitions(*keys, "test")
    return ordered.mapInArrow(apply, made).groupBy(*keys, "share", "test").agg(F.max("n_bins").alias("n_bins"), F.sum("n").alias("n"), F.sum("bits").alias("bits"))


def holdout_cost(values: DataFrame, is_test, share: int) -> DataFrame:
    """vtype, n_bins, in_sample, hold_out: bits a value of adaptive bins fitted on the other rows, on both parts."""
    c = held_costs(histogram(values.select("vtype", "v", is_test.alias("test")), ["vtype", "test"]), ["vtype"], [share])
    part = lambda test: F.round(F.sum(F.when(F.col("test") == test, F.col("bits"))) / F.sum(F.when(F.col("test") == test, F.col("n"))), 4)
    return c.groupBy("vtype").agg(F.max("n_bins").cast("int").alias("n_bins"), part(False).alias("in_sample"), part(True).alias("hold_out"))


def first_channels(values: DataFrame) -> DataFrame:
    """event, pointer (the channel of the least start; the lowest number on ties), active, zeros, pulses (all of the event)."""
    s = values.where("vtype in ('start', 'pulses')")
    start = F.when(F.col("vtype") == "start", F.col("v"))
    return s.groupBy("event").agg(
        F.min(F.when(F.col("vtype") == "start", F.struct("v", "channel"))).getField("channel").alias("pointer"),
        F.count(start).alias("active"), F.count_if(start == 0).alias("zeros"), F.sum(F.when(F.col("vtype") == "pulses", F.col("v"))).alias("pulses"),
    )


def zero_pointer_cost(values: DataFrame, by_pulses: bool = False) -> DataFrame:
    """events, flag_bits (zeros told by a flag at each start), pointer_bits, saved: bits an event.

    pointer: uniform over the active channels of the event, plus a tie flag; by_pulses: the probability of each channel
    given its number of pulses and the number of active channels."""
    f = first_channels(values)
    g = f.agg(F.count(F.lit(1)).alias("events"), F.sum("active").alias("a"), F.sum("zeros").alias("z"), F.sum(F.log2("active")).alias("uniform"), F.sum((F.col("zeros") > 1).cast("long")).alias("ties"))
    h = lambda k, n: F.when((k > 0) & (k < n), n * F.log2(n) - k * F.log2(k) - (n - k) * F.log2(n - k)).otherwise(0.0)
    pointer = F.col("uniform")
    if by_pulses:
        p = values.where("vtype = 'pulses'").select("event", "channel", F.col("v").alias("own"))
        both = p.join(f.select("event", "pointer", "active"), "event").withColumn("first", (F.col("channel") == F.col("pointer")).cast("long"))
        rate = both.groupBy("own", "active").agg((F.sum("first") / F.count(F.lit(1))).alias("rate"))
        both = both.join(F.broadcast(rate), ["own", "active"])
        cost = both.groupBy("event").agg((F.log2(F.sum("rate")) - F.log2(F.sum(F.col("rate") * F.col("first")))).alias("bits")).agg(F.sum("bits").alias("conditional"))
        g, pointer = g.crossJoin(F.broadcast(cost)), F.col("conditional")
    pointer = pointer + h(F.col("ties"), F.col("events"))
    flags = h(F.col("z"), F.col("a"))
    return g.select("events", F.round(flags / F.col("events"), 4).alias("flag_bits"), F.round(pointer / F.col("events"), 4).alias("pointer_bits"), F.round((flags - pointer) / F.col("events"), 4).alias("saved"))


def class_entropy(pulses: DataFrame) -> DataFrame:
    """event_class, total, symbols, entropy of the numbers of pulses in each class."""
    e = entropy(pulses.groupBy("event_class", F.col("pulses").alias("v")).agg(F.count(F.lit(1)).alias("n")), ["event_class"])
    return e.select("event_class", F.col("total").cast("long").alias("total"), "symbols", F.round("entropy", 4).alias("entropy"))
