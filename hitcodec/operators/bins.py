"""Bins of numeric values: the top bits, adaptive power-of-two widths, look-up tables, and what they cost.

Bins: bin, bin_start, bin_width (low bits left raw), n. A value is its bin (entropy coded) and value - bin_start raw.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from hitcodec.functions.bits import bit_length
from hitcodec.operators.histo import cumulative, entropy
from hitcodec.operators.prefix import huffman_bits
from hitcodec.sources.views import div


def simple_bins(hist: DataFrame, keys: list[str], low_bits: int) -> DataFrame:
    """keys, bin (the bits above low_bits), n; only occupied bins."""
    return hist.groupBy(*keys, F.shiftright("v", low_bits).alias("bin")).agg(F.sum("n").alias("n"))


def simple_bin_sweep(hist: DataFrame, keys: list[str], low_bits: list[int]) -> DataFrame:
    """keys, low_bits, n_bins, coded, raw, total (bits a value): counted at the finest level, then rolled up."""
    least = min(low_bits)
    fine = hist.groupBy(*keys, F.shiftright("v", least).alias("b")).agg(F.sum("n").alias("n"))
    each = fine.withColumn("low_bits", F.explode(F.array(*[F.lit(x) for x in sorted(low_bits)])))
    coarse = each.groupBy(*keys, "low_bits", F.expr(f"shiftright(b, low_bits - {least})").alias("bin")).agg(F.sum("n").alias("n"))
    e = entropy(coarse, [*keys, "low_bits"])
    return e.select(*keys, "low_bits", F.col("symbols").alias("n_bins"), F.round("entropy", 4).alias("coded"), F.col("low_bits").cast("double").alias("raw"), F.round(F.col("entropy") + F.col("low_bits"), 4).alias("total"))


def greedy_bins(v: np.ndarray, n: np.ndarray, min_val: int, strict: bool = True, special: list[int] | None = None) -> list[tuple[int, int, int]]:
    """(start, width, count) of bins over sorted distinct values v with counts n.

    A bin grows, a bit of width at a time, until it holds more than min_val values (at least, if not strict) or covers the
    rest: the value that must be inside gives the width at once. `special` values get a bin of width 0 each.
    """
    if special:
        own = np.isin(v, special)
        found = [(int(a), 0, int(b)) for a, b in zip(v[own], n[own])]
        cuts, parts = [-1, *np.flatnonzero(own).tolist(), len(v)], []
        for a, b in zip(cuts, cuts[1:]):
            if b - a > 1:
                parts += _capped(greedy_bins(v[a + 1 : b], n[a + 1 : b], min_val, strict), int(v[b]) if b < len(v) else None, v[a + 1 : b], n[a + 1 : b])
        return sorted(found + parts)
    cum = np.cumsum(n)
    total, i, s, out = int(cum[-1]), 0, int(v[0]), []
    need = min_val if strict else max(min_val - 1, 0)
    while i < total:
        t = int(v[np.searchsorted(cum, min(i + need, total - 1), "right")])
        w = max(0, t - s).bit_length()
        k = int(np.searchsorted(v, s + (1 << w), "left"))
        after = int(cum[k - 1]) if k else 0
        out.append((s, w, after - i))
        s, i = s + (1 << w), after
    return out


def _capped(bins, end, v, n):
    """Bins that may not reach a special value: the last is halved until it ends before."""
    if end is None or not bins or bins[-1][0] + (1 << bins[-1][1]) <= end:
        return bins
    s, w, _ = bins.pop()
    while s < end:
        while s + (1 << w) > end:
            w -= 1
        inside = (v >= s) & (v < s + (1 << w))
        if inside.any():
            bins.append((s, w, int(n[inside].sum())))
        s += 1 << w
    return bins


class GreedyStream:
    """The same bins from sorted values that come in parts; nothing but the open bin's place is held."""

    def __init__(self, total: int, min_val: int, strict: bool = True):
        self.total, self.need = total, min_val if strict else max(min_val - 1, 0)
        self.start = self.end = None  # of the open bin; its end once the value that must be inside is known
        self.done = self.passed = 0  # values in closed bins, values seen

    def feed(self, v: np.ndarray, n: np.ndarray) -> list[tuple[int, int, int]]:
        cum = self.passed + np.cumsum(n)
        if self.start is None:
            self.start = int(v[0])
        out = []
        while self.done < self.total:
            if self.end is None:
                k = int(np.searchsorted(cum, min(self.done + self.need, self.total - 1), "right"))
                if k == len(v):
                    break
                self.width = max(0, int(v[k]) - self.start).bit_length()
                self.end = self.start + (1 << self.width)
            k = int(np.searchsorted(v, self.end, "left"))
            after = int(cum[k - 1]) if k else self.passed
            if k == len(v) and after < self.total:
                break
            out.append((self.start, self.width, after - self.done))
            self.start, self.end, self.done = self.end, None, after
        self.passed = int(cum[-1])
        return out


BINS = "bin int, bin_start long, bin_width int, n long"


def adaptive_bins(hist: DataFrame, keys: list[str], min_val: int | None = None, share: int = 256, strict: bool = True, special: list[int] | None = None) -> DataFrame:
    """keys, bin, bin_start, bin_width, n. min_val values, or the count of the group div `share`.

    The groups are fitted in parallel. A group's distinct values are sorted by Spark (spilling where they must) and
    stream through one task in Arrow batches, of which it holds one; only `special` values, which cut the domain, make a
    task hold a group's distinct values. `adaptive_bins_sketch` needs neither sort nor stream."""
    if special:
        return _special_bins(hist, keys, min_val, share, strict, special)
    one = hist.withColumn("share", F.lit(share)) if min_val is None else hist.withColumn("share", F.lit(0))
    return _streamed_bins(one, keys, min_val, strict).drop("share")


def _streamed_bins(hist: DataFrame, keys: list[str], min_val: int | None = None, strict: bool = True) -> DataFrame:
    """Bins for each group and each of its shares (arrays are taken apart in the task, so that no row is repeated)."""
    several = hist.schema["share"].dataType.simpleString().startswith("array")
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in hist.schema.fields if f.name in keys)
    totals = hist.groupBy(*keys).agg(F.sum("n").alias("_total"))
    same = F.lit(True)
    for k in keys:
        totals = totals.withColumnRenamed(k, f"_{k}")
        same = same & F.col(k).eqNullSafe(F.col(f"_{k}"))
    rows = hist.select(*keys, "v", F.col("n").cast("long").alias("n"), "share").join(totals, same).select(F.struct(*keys).alias("key"), "v", "n", "share", "_total")
    rows = rows.repartition("key").sortWithinPartitions("key", "v")

    def apply(batches):
        now, streams = None, []
        for batch in batches:
            key, v, n = batch.column(0), batch.column(1).to_numpy(), batch.column(2).to_numpy()
            cuts = [0, *_changes(key), batch.num_rows]
            for a, z in zip(cuts, cuts[1:]):
                here = key[a].as_py()
                if here != now:
                    total, shares = batch.column(4)[a].as_py(), batch.column(3)[a].as_py()
                    least = lambda s: total // s if min_val is None else min_val  # noqa: E731, B023
                    now, streams = here, [[s, GreedyStream(total, least(s), strict), 0] for s in (shares if several else [shares])]
                found = []
                for held in streams:
                    for s, w, count in held[1].feed(v[a:z], n[a:z]):
                        found.append({**here, "share": held[0], "bin": held[2], "bin_start": s, "bin_width": w, "n": count})
                        held[2] += 1
                if found:
                    yield pa.RecordBatch.from_pylist(found, schema)

    made = StructType.fromDDL(f"{kinds}, share int, {BINS}")
    schema = to_arrow_schema(made)
    return rows.mapInArrow(apply, made)


def _changes(key: pa.Array) -> list[int]:
    """Where the keys of sorted rows change."""
    changed = np.zeros(max(len(key) - 1, 0), bool)
    for k in range(key.type.num_fields):
        f = pc.dictionary_encode(key.field(k), null_encoding="encode").indices.to_numpy()
        changed |= f[1:] != f[:-1]
    return (np.flatnonzero(changed) + 1).tolist()


def _special_bins(hist: DataFrame, keys: list[str], min_val: int | None, share: int, strict: bool, special: list[int]) -> DataFrame:
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in hist.schema.fields if f.name in keys)

    def one(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("v")
        v, n = part["v"].to_numpy(np.int64), part["n"].to_numpy(np.int64)
        rows = greedy_bins(v, n, int(n.sum()) // share if min_val is None else min_val, strict, special)
        out = pd.DataFrame([(k, *r) for k, r in enumerate(rows)], columns=["bin", "bin_start", "bin_width", "n"])
        for name, x in zip(keys, key):
            out[name] = x
        return out[[*keys, "bin", "bin_start", "bin_width", "n"]]

    return hist.select(*keys, "v", "n").groupBy(*keys).applyInPandas(one, f"{kinds}, {BINS}")


def adaptive_bins_sketch(values: DataFrame, keys: list[str], share: int = 256, accuracy: int = 10_000) -> DataFrame:
    """Bins from approximate quantiles (one pass, bounded memory), then counted exactly: starts snap the quantiles."""
    grid = [k / share for k in range(share + 1)]
    q = values.groupBy(*keys).agg(F.array_sort(F.array_distinct(F.percentile_approx("v", grid, accuracy))).alias("q"))
    local = q.collect()  # a row of `share` numbers for each group
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in q.schema.fields if f.name in keys)
    rows = []
    for r in local:
        v = np.array(r["q"], np.int64)
        for k, (s, w, _) in enumerate(greedy_bins(v, np.ones(len(v), np.int64), 1)):
            rows.append((*[r[x] for x in keys], k, s, w))
    bins = values.sparkSession.createDataFrame(rows, f"{kinds}, bin int, bin_start long, bin_width int")
    return count_bins(values, bins, keys)


def count_bins(values: DataFrame, bins: DataFrame, keys: list[str]) -> DataFrame:
    """Exact counts of values in bins (those outside go to the first or last bin). Some hundred bins a group travel in a closure."""
    edges: dict[tuple, list[int]] = {}
    for r in bins.select(*keys, "bin_start").orderBy("bin_start").collect():
        edges.setdefault(tuple(r[k] for k in keys), []).append(r["bin_start"])
    hist = values.groupBy(*keys, "v").agg(F.count(F.lit(1)).alias("n"))
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in values.schema.fields if f.name in keys)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cuts = [0, *_changes(batch.select(keys).to_struct_array()), batch.num_rows]
            at = np.zeros(batch.num_rows, np.int32)
            v = batch.column(len(keys)).to_numpy()
            for a, z in zip(cuts, cuts[1:]):
                own = edges[tuple(batch.column(k)[a].as_py() for k in range(len(keys)))]
                at[a:z] = np.maximum(np.searchsorted(own, v[a:z], "right") - 1, 0)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keys)], pa.array(at), batch.column(len(keys) + 1)], [*keys, "bin", "n"])

    placed = hist.select(*keys, "v", "n").sortWithinPartitions(*keys).mapInArrow(apply, f"{kinds}, bin int, n long")
    counted = placed.groupBy(*keys, "bin").agg(F.sum("n").alias("n"))
    return bins.select(*keys, "bin", "bin_start", "bin_width").join(counted, [*keys, "bin"], "left").withColumn("n", F.coalesce("n", F.lit(0)))


def bin_cost(bins: DataFrame, keys: list[str]) -> DataFrame:
    """keys, n_values, n_bins, coded, raw, total: bits a value with an accurate coder."""
    used = bins.where("n > 0")
    e = entropy(used, keys)
    raw = used.groupBy(*keys).agg((F.sum(F.col("bin_width") * F.col("n")) / F.sum("n")).alias("raw"))
    return e.join(raw, keys).select(*keys, F.col("total").cast("long").alias("n_values"), F.col("symbols").alias("n_bins"), F.round("entropy", 4).alias("coded"), F.round("raw", 4).alias("raw"), F.round(F.col("entropy") + F.col("raw"), 4).alias("total"))


def adaptive_sweep(hist: DataFrame, keys: list[str], shares: list[int]) -> DataFrame:
    """keys, share, and the cost of adaptive bins with min_val = count div share: one histogram, one stream for all shares."""
    each = hist.withColumn("share", F.lit([int(x) for x in shares]))
    return bin_cost(_streamed_bins(each, keys), [*keys, "share"])


def simple_huffman(hist: DataFrame, keys: list[str], top_bits: int = 8) -> DataFrame:
    """keys, n_values, n_bins, low_bits, coded_bits (all values): Huffman words for the top bits of the greatest value."""
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in hist.schema.fields if f.name in keys)
    top = hist.groupBy(*keys).agg(F.greatest(F.lit(0), bit_length(F.max("v")) - top_bits).alias("low_bits"))
    coarse = hist.join(F.broadcast(top), keys).groupBy(*keys, "low_bits", F.expr("shiftright(v, low_bits)").alias("b")).agg(F.sum("n").alias("n"))

    def one(key: tuple, part: pd.DataFrame) -> pd.DataFrame:  # at most 2**top_bits rows
        out = pd.DataFrame({"n_values": [int(part["n"].sum())], "n_bins": [len(part)], "coded_bits": [huffman_bits(part["n"].tolist())]})
        for name, x in zip([*keys, "low_bits"], key):
            out[name] = x
        return out[[*keys, "low_bits", "n_values", "n_bins", "coded_bits"]]

    return coarse.groupBy(*keys, "low_bits").applyInPandas(one, f"{kinds}, low_bits int, n_values long, n_bins long, coded_bits long")


def optimal_bins(v: np.ndarray, n: np.ndarray, max_bins: int) -> tuple[float, list[tuple[int, int, int]]]:
    """Least cost (bits of all values) over contiguous power-of-two bins, by dynamic programming; small domains only.

    The entropy of a bin is -log2 of its share, so that the costs of bins add up."""
    lo, hi, total = int(v[0]), int(v[-1]), float(n.sum())
    if hi - lo > 4096:
        raise ValueError("the domain is too large")
    dense = np.zeros(hi - lo + 1, np.int64)
    dense[v - lo] = n
    cum = np.concatenate([[0], np.cumsum(dense)])
    size = len(dense)
    best: list[dict[int, tuple[float, tuple]]] = [{0: (0.0, ())}]
    for _ in range(max_bins):
        nxt: dict[int, tuple[float, tuple]] = {}
        for at, (cost, path) in best[-1].items():
            if at >= size:
                continue
            w = 0
            while True:
                end = min(size, at + (1 << w))
                c = int(cum[end] - cum[at])
                add = c * (w - np.log2(c / total)) if c else 0.0
                key = min(at + (1 << w), size)
                if key not in nxt or cost + add < nxt[key][0]:
                    nxt[key] = (cost + add, (*path, (lo + at, w, c)))
                if at + (1 << w) >= size:
                    break
                w += 1
        best.append(nxt)
    done = min((b[size] for b in best if size in b), key=lambda x: x[0])
    return float(done[0]), list(done[1])


def lookup_table(starts: list[int], widths: list[int], bits: int = 8) -> tuple[list[int], int, int]:
    """Nested tables on leading bits: flat entries, levels, and the bits of all levels.

    Entry e >= 0 is a bin, e < 0 the node -e; node k holds entries k << bits and on. Values are taken less starts[0]."""
    first = starts[0]
    span = max(s - first + (1 << w) for s, w in zip(starts, widths))
    levels = max(1, -(-max(1, (span - 1).bit_length()) // bits))
    edges = np.array(starts, np.int64) - first
    table: list[int] = []

    def fill(low: int, level: int) -> int:
        node = len(table) >> bits
        table.extend([0] * (1 << bits))
        step = 1 << (bits * (levels - 1 - level))
        for k in range(1 << bits):
            a, b = low + k * step, low + (k + 1) * step - 1
            x, y = (int(np.searchsorted(edges, e, "right")) - 1 for e in (a, b))
            table[(node << bits) + k] = x if x == y else -fill(a, level + 1)
        return node

    fill(0, 0)
    return table, levels, bits * levels


def assign_bin_lut(df: DataFrame, starts: list[int], widths: list[int], v: str = "v", to: str = "bin", bits: int = 8) -> DataFrame:
    """Adds the bin of each value by nested table look-ups: no search and no join."""
    table, levels, _ = lookup_table(starts, widths, bits)
    flat, x = F.lit(table), F.greatest(F.lit(0), F.least(F.col(v) - starts[0], F.lit((1 << (bits * levels)) - 1)))
    df = df.withColumn("_x", x)
    found: Column = F.lit(0)
    for level in range(levels):
        digit = F.shiftright("_x", bits * (levels - 1 - level)).bitwiseAND(F.lit((1 << bits) - 1))
        entry = lambda node: F.element_at(flat, (node * (1 << bits) + digit + 1).cast("int"))  # noqa: E731, B023
        name = f"_e{level}"
        df = df.withColumn(name, entry(F.lit(0)) if level == 0 else F.when(F.col(f"_e{level - 1}") < 0, entry(-F.col(f"_e{level - 1}"))).otherwise(F.col(f"_e{level - 1}")))
        found = F.col(name)
    return df.withColumn(to, found.cast("int")).drop("_x", *[f"_e{k}" for k in range(levels)])


def assign_bin_join(df: DataFrame, bins: DataFrame, v: str = "v") -> DataFrame:
    """The baseline of the look-up: a range join with the (small) table of bins, as a nested loop."""
    b = F.broadcast(bins.select("bin", F.col("bin_start").alias("_s"), (F.col("bin_start") + F.expr("shiftleft(1L, bin_width)")).alias("_e")))
    return df.join(b, (F.col(v) >= F.col("_s")) & (F.col(v) < F.col("_e"))).drop("_s", "_e")


def assign_bin_range(df: DataFrame, bins: DataFrame, v: str = "v", cell: int = 1024) -> DataFrame:
    """The same by an equi-join on cells of the value axis and a check: for bin tables that are not small."""
    b = bins.select("bin", F.col("bin_start").alias("_s"), (F.col("bin_start") + F.expr("shiftleft(1L, bin_width)")).alias("_e"))
    b = b.withColumn("_cell", F.explode(F.sequence(div(F.col("_s"), cell), div(F.col("_e") - 1, cell))))
    return df.withColumn("_cell", div(F.col(v), cell)).join(b, "_cell").where((F.col(v) >= F.col("_s")) & (F.col(v) < F.col("_e"))).drop("_s", "_e", "_cell")


def value_from_bin(df: DataFrame, bins: DataFrame) -> DataFrame:
    """v = bin_start + raw."""
    return df.join(F.broadcast(bins.select("bin", "bin_start")), "bin").withColumn("v", F.col("bin_start") + F.col("raw"))


def fuse_bins(model: dict, starts: list[int], widths: list[int]) -> dict[str, np.ndarray]:
    """A decoder table that gives bin start and width in place of the bin: one look-up less."""
    dec = model["dec"]
    return {"start": np.array(starts, np.int64)[dec["sym"]], "width": np.array(widths, np.int64)[dec["sym"]], "nbits": dec["nbits"], "base": dec["base"]}


def bin_uniformity(hist: DataFrame, bins: DataFrame, keys: list[str]) -> DataFrame:
    """keys, bin, n, gap: the greatest distance of the distribution inside a bin from the uniform one."""
    b = bins.select(*keys, "bin", "bin_start", "bin_width")
    placed = hist.join(F.broadcast(b), keys).where(F.expr("v >= bin_start and v < bin_start + shiftleft(1L, bin_width)"))
    w = Window.partitionBy(*keys, "bin").orderBy("v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    all_ = Window.partitionBy(*keys, "bin")
    share = F.sum("n").over(w) / F.sum("n").over(all_)
    even = (F.col("v") - F.col("bin_start") + 1) / F.expr("shiftleft(1L, bin_width)")
    return placed.withColumn("_gap", F.abs(share - even)).groupBy(*keys, "bin").agg(F.sum("n").alias("n"), F.round(F.max("_gap"), 6).alias("gap"))


def with_cumulative(hist: DataFrame, keys: list[str]) -> DataFrame:
    """The histogram with ranks, for threshold look-ups at scale."""
    return cumulative(hist, keys)
