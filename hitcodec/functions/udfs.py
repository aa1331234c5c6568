"""The UDF surface: Arrow and pandas functions, a grouped aggregate, table functions and their SQL names."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F


def _expgolomb_len(v: pa.Array) -> pa.Array:
    x = np.asarray(v, np.float64) + 1
    return pa.array((2 * (np.frexp(x)[1] - 1) + 1).astype(np.int32))


def expgolomb_len():
    """Bits of Exp-Golomb words, a whole Arrow column at a time."""
    return F.arrow_udf(_expgolomb_len, "int")


def assign_bin_np(starts: list[int]):
    """Bins of values by binary search over starts."""
    edges = np.array(starts, np.int64)

    def f(v: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(edges, v.to_numpy(np.int64), "right") - 1, dtype="int32")

    return F.pandas_udf(f, "int")


def _entropy_bits(sym: pd.Series) -> float:
    n = sym.value_counts().to_numpy(np.float64)
    return float(np.log2(n.sum()) - (n * np.log2(n)).sum() / n.sum())


def entropy_bits():
    """Entropy of a group's symbols; a group meets in one task, so that it is for small groups (histograms else)."""
    return F.pandas_udf(_entropy_bits, "double")


def trace_udtf():
    """Table function: steps of the coder of four states over a string of a's and b's."""
    from hitcodec.operators import tans

    model = tans.model_of(np.array([0, 1, 0, 0]), 2)

    class Trace:
        def eval(self, text: str):
            for row in tans.trace(["ab".index(c) for c in text], model, 4):
                yield row[0], "ab"[row[1]], row[2], row[4], row[5]

    return F.udtf(Trace, returnType="step int, sym string, state int, bits string, next_state int")


def decode_udtf(symbols: int):
    """Table function: the symbols of an Exp-Golomb bit string, one after the other; one beyond the alphabet is an error."""

    class Decode:
        def eval(self, bits: str):
            at = pos = 0
            while at < len(bits):
                zeros = bits.index("1", at) - at
                value = int(bits[at + zeros : at + 2 * zeros + 1], 2) - 1
                if value >= symbols:
                    raise ValueError(f"symbol {value} is beyond the alphabet of {symbols}")
                yield pos, value
                at, pos = at + 2 * zeros + 1, pos + 1

    return F.udtf(Decode, returnType="pos int, sym int")


def register_all(spark) -> None:
    """The functions under SQL names."""
    spark.udf.register("expgolomb_len", expgolomb_len())
    spark.udtf.register("tans_trace", trace_udtf())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION information_bits(p DOUBLE) RETURNS DOUBLE RETURN -log2(p)")


def max_gap(v: pa.Array) -> int:
    """Greatest step between neighbours of a sorted column."""
    return pc.max(pc.pairwise_diff(v)).as_py() or 0
