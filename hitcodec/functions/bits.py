"""Bit-level column functions: lengths, unary and Exp-Golomb words, zig-zag, base-m blocks. All stay in the JVM."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def bit_length(x: Column | str) -> Column:
    """Bits of a non-negative integer: 1 for 0 and 1."""
    return F.length(F.bin(_c(x)))


def raw_bits(x: Column | str) -> Column:
    """Bits that tell the values 0..x apart: 0 for 0."""
    return F.when(_c(x) == 0, 0).otherwise(F.length(F.bin(_c(x))))


def zigzag(x: Column | str) -> Column:
    """0, -1, 1, -2, ... to 0, 1, 2, 3, ..."""
    x = _c(x)
    return F.shiftleft(x, 1).bitwiseXOR(F.shiftright(x, 63))


def unzigzag(z: Column | str) -> Column:
    z = _c(z)
    return F.shiftrightunsigned(z, 1).bitwiseXOR(-z.bitwiseAND(F.lit(1)))


def unary_bits(x: Column | str) -> Column:
    return _c(x) + 1


def unary_encode(x: Column | str) -> Column:
    return F.concat(F.repeat(F.lit("1"), _c(x).cast("int")), F.lit("0"))


def unary_decode(word: Column | str) -> Column:
    return F.instr(_c(word), "0").cast("long") - 1


def expgolomb_bits(x: Column | str) -> Column:
    """2 floor(lg(x + 1)) + 1."""
    return bit_length(_c(x) + 1) * 2 - 1


def expgolomb_encode(x: Column | str) -> Column:
    """Zeros, one less than the bits of x + 1, then those bits."""
    word = F.bin(_c(x) + 1)
    return F.concat(F.repeat(F.lit("0"), F.length(word) - 1), word)


def expgolomb_decode(word: Column | str) -> Column:
    return F.conv(F.ltrim(_c(word), F.lit("0")), 2, 10).cast("long") - 1


def radix_block(m: int) -> int:
    """Digits of base m that fit 63 bits."""
    return int(63 / math.log2(m))


def radix_pack(digits: Column | str, m: int) -> Column:
    """An array of digits below m as one number (the first digit is the most significant)."""
    return F.aggregate(_c(digits), F.lit(0).cast("long"), lambda a, d: a * m + d)


def radix_unpack(packed: Column | str, n: Column | str, m: int) -> Column:
    """The n digits of a packed number."""
    powers = F.array(*[F.lit(m**k).cast("long") for k in range(radix_block(m))])
    return F.transform(F.sequence(_c(n), F.lit(1), F.lit(-1)), lambda k: F.call_function("div", _c(packed), F.element_at(powers, k)) % m)
