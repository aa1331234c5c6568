"""The experiment workloads, each one call over any hits view or values table."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hitcodec.functions import bits as B
from hitcodec.operators import bins as BN
from hitcodec.operators import fec as FEC
from hitcodec.operators import frames as FR
from hitcodec.operators import histo as H
from hitcodec.operators import layout as L
from hitcodec.operators import models as M
from hitcodec.operators import rangecoder as RC
from hitcodec.operators import tans as T
from hitcodec.plans.cost import ladder

__all__ = ["ladder"]


def distributions(hits: DataFrame, n_channels: int, points: int = 101) -> tuple[DataFrame, DataFrame]:
    """(empirical distributions of the numeric types, shares of the numbers of pulses)."""
    return H.ecdf(L.value_streams(hits).where("vtype <> 'pulses'"), points), L.pulse_frequencies(hits, n_channels)


def pulse_coder_table(counts: DataFrame) -> DataFrame:
    """coder, bits: six ways to code the numbers of pulses, from their counts (v, n)."""
    n = F.sum("n")
    hist = counts.select(F.lit("pulses").alias("vtype"), "v", "n")
    simple = hist.agg(
        F.round(n * B.bit_length(F.max("v")) / n, 4).alias("fixed"), F.round(F.log2(F.max("v") + 1), 4).alias("radix"),
        F.round(F.sum(F.col("n") * (F.col("v") + 1)) / n, 4).alias("unary"), F.round(F.sum(F.col("n") * B.expgolomb_bits("v")) / n, 4).alias("expgolomb"),
        F.round(F.log2(n) - F.sum(F.col("n") * F.log2("n")) / n, 4).alias("entropy"),
    )
    huffman = BN.simple_huffman(hist, ["vtype"]).select(F.round(F.col("coded_bits") / F.col("n_values"), 4).alias("huffman"))
    return simple.crossJoin(huffman).select(F.expr("stack(6, 'fixed', fixed, 'radix', radix, 'unary', unary, 'expgolomb', expgolomb, 'huffman', huffman, 'entropy', entropy) as (coder, bits)"))


def tans_loss_sweep(counts: DataFrame, r_values: list[int], spreads: tuple[str, ...] = ("step", "block", "reverse", "precise")) -> DataFrame:
    """symbols, m, r, spread, entropy, loss, table_bytes: every table of the grid in its own task.

    counts: symbols (a name), v, n; a name's alphabet is small."""
    grid = counts.groupBy("symbols").agg(F.array_sort(F.collect_list(F.struct("v", "n"))).alias("c"))
    grid = grid.withColumn("r", F.explode(F.array(*[F.lit(r) for r in r_values]))).withColumn("spread", F.explode(F.array(*[F.lit(s) for s in spreads])))
    grid = grid.where(F.expr("shiftleft(1, r) >= size(c)"))

    def one(batches):
        for batch in batches:
            out = []
            for name, c, r, spread in zip(*(x.to_pylist() for x in batch.columns)):
                n = np.array([x["n"] for x in c], np.float64)
                model = T.fit(n, r, spread)
                got = T.loss(model, n)
                out.append((name, len(n), r, spread, round(float(got["entropy"]), 6), round(float(got["loss"]), 6), T.table_bytes(model)))
            yield pa.RecordBatch.from_pandas(pd.DataFrame(out, columns=["symbols", "m", "r", "spread", "entropy", "loss", "table_bytes"]).astype({"m": "int32", "r": "int32"}), preserve_index=False)

    return grid.select("symbols", "c", "r", "spread").repartition("symbols", "r", "spread").mapInArrow(one, "symbols string, m int, r int, spread string, entropy double, loss double, table_bytes long")


def bin_comparison(hist: DataFrame, low_bits: list[int], shares: list[int]) -> DataFrame:
    """vtype, kind, setting, n_bins, coded, raw, total: simple and adaptive bins side by side."""
    a = BN.simple_bin_sweep(hist, ["vtype"], low_bits).select("vtype", F.lit("simple").alias("kind"), F.col("low_bits").alias("setting"), "n_bins", "coded", "raw", "total")
    b = BN.adaptive_sweep(hist, ["vtype"], shares).select("vtype", F.lit("adaptive").alias("kind"), F.col("share").alias("setting"), "n_bins", "coded", "raw", "total")
    return a.unionByName(b)


def scope_sweep(values: DataFrame, shares: list[int], is_test: Column, classes: DataFrame | None = None) -> DataFrame:
    """scope, share, models, n_bins, in_sample, hold_out, table_bits: one table or one for each channel (or class), with
    the budget of bins varied, scored on the rows they were fitted on and on the others."""
    out = None
    for scope in ("global", "channel") + (("class",) if classes is not None else ()):
        h = M.scope_values(values, scope, classes).select("scope_id", "v", is_test.alias("test")).groupBy("scope_id", "test", "v").agg(F.count(F.lit(1)).alias("n"))
        c = M.held_costs(h, ["scope_id"], shares)
        part = lambda name, test: F.coalesce(F.sum(F.when(F.col("test") == test, F.col(name))), F.lit(0))
        each = c.groupBy("scope_id", "share").agg(F.max("n_bins").alias("n_bins"), part("bits", False).alias("a"), part("n", False).alias("na"), part("bits", True).alias("b"), part("n", True).alias("nb"))
        g = each.groupBy("share").agg(F.count(F.lit(1)).alias("models"), F.sum("n_bins").alias("n_bins"), F.round(F.sum("a") / F.sum("na"), 3).alias("in_sample"), F.round(F.sum("b") / F.sum("nb"), 3).alias("hold_out"))
        g = g.select(F.lit(scope).alias("scope"), "share", "models", "n_bins", "in_sample", "hold_out", M.model_bits("n_bins").alias("table_bits"))
        out = g if out is None else out.unionByName(g)
    return out


def throughput(frames: list[np.ndarray], counts) -> dict[str, float]:
    """Symbols (bytes) a second of one core, in MB, for the coder and the multiplying baseline."""
    size, model, cum, found = sum(map(len, frames)) / 1e6, T.fit(counts), RC.model(counts), {}

    def timed(name, f, *args):
        began = time.process_time()
        out = f(*args)
        found[name] = size / max(1e-9, time.process_time() - began)
        return out

    coded = timed("tans_encode", T.encode_frames, frames, model)
    timed("tans_decode", T.decode_frames, [(*c, len(f)) for c, f in zip(coded, frames)], model)
    data = timed("range_encode", RC.range_encode, frames, cum)
    timed("range_decode", RC.range_decode, data, [len(f) for f in frames], cum)
    return found


def archive(hits: DataFrame, path: str, n_channels: int, **options) -> dict:
    """Fit, encode and write; returns the models that `restore` needs."""
    models = FR.fit_models(hits, n_channels)
    FR.write_frames(FR.encode(hits, models, n_channels, **options), path)
    return models


def restore(spark, path: str, models: dict, n_channels: int) -> DataFrame:
    return FR.decode(FR.sound(FR.read_frames(spark, path)), models, n_channels)


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """How many rows either side has that the other lacks."""
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("differ"))


def fault_study(frames: DataFrame, every: int) -> DataFrame:
    """frames, damaged, detected, repaired: of frames with one bit turned, those whose checksum fails, and those that a
    Hamming layer under the same damage gives back whole."""
    from hitcodec.operators.fec import hamming_decode, hamming_encode

    bad = FR.verify(FR.flip_bits(frames, every))

    def repair(batches):
        for batch in batches:
            out = []
            for frame, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                hit = frame % every == 0 and len(data) > 0
                coded = bytearray(hamming_encode(data))
                if hit:
                    coded[0] ^= 0x10
                out.append((hit, hit and hamming_decode(bytes(coded), len(data))[0] == data))
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.bool_()), pa.array([x[1] for x in out], pa.bool_())], ["hit", "good"])

    mended = frames.select("frame", "width_payload").mapInArrow(repair, "hit boolean, good boolean").agg(F.count(F.lit(1)).alias("frames"), F.count_if("hit").alias("damaged"), F.count_if("good").alias("repaired"))
    return mended.crossJoin(bad.agg(F.count_if(~F.col("ok")).alias("detected"))).select("frames", "damaged", "detected", "repaired")


def fec_encode(frames: DataFrame, scheme: str = "hamming74", column: str = "width_payload") -> DataFrame:
    """frame, size, protected: a payload column under a layer that repairs single bits (7/4 of its size), or the parity of
    the payload's four quarters after it (5/4)."""
    if scheme not in ("hamming74", "xor_parity"):
        raise ValueError(f"no such scheme: {scheme}")

    def apply(batches):
        for batch in batches:
            data = batch.column(1).to_pylist()
            made = [FEC.hamming_encode(x) if scheme == "hamming74" else x + FEC.parity_encode(_quarters(x)) for x in data]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(x) for x in data], pa.int64()), pa.array(made, pa.binary())], ["frame", "size", "protected"])

    return frames.select("frame", column).mapInArrow(apply, "frame long, size long, protected binary")


def _quarters(x: bytes) -> list[bytes]:
    step = -(-len(x) // 4)
    return [x[k * step : (k + 1) * step] for k in range(4)]


def fec_decode(protected: DataFrame, scheme: str = "hamming74", lost_quarter: int | None = None) -> DataFrame:
    """frame, payload, repaired (words made good, or quarters rebuilt); `lost_quarter` is treated as missing."""

    def apply(batches):
        for batch in batches:
            out = []
            for frame, size, data in zip(*(c.to_pylist() for c in batch.columns)):
                if scheme == "hamming74":
                    out.append((frame, *FEC.hamming_decode(data, size)))
                    continue
                parts, parity = _quarters(data[:size]), data[size:]
                sizes = [len(p) for p in parts]
                if lost_quarter is not None:
                    parts[lost_quarter] = None
                out.append((frame, b"".join(FEC.parity_repair(parts, sizes, parity)), int(lost_quarter is not None)))
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], t) for k, t in enumerate((pa.int64(), pa.binary(), pa.int64()))], ["frame", "payload", "repaired"])

    return protected.select("frame", "size", "protected").mapInArrow(apply, "frame long, payload binary, repaired long")
