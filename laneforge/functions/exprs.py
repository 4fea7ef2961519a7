"""Column functions of the relational plane."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .layout import LIMIT


def bit_length(v: Column) -> Column:
    """Bits of an unsigned integer; 0 for 0. Exact: the binary digits, not a logarithm."""
    return F.when(v == 0, 0).otherwise(F.length(F.bin(v))).cast("int")


def low_bits(v: Column, b: Column) -> Column:
    return v.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), b) - 1)


def high_bits(v: Column, b: Column) -> Column:
    return F.call_function("shiftrightunsigned", v, b)


def zigzag(v: Column) -> Column:
    """Signed to unsigned, small magnitudes first."""
    return F.shiftleft(v, 1).bitwiseXOR(F.shiftright(v, 63))


def unzigzag(v: Column) -> Column:
    return F.shiftrightunsigned(v, 1).bitwiseXOR(-v.bitwiseAND(F.lit(1)))


def vbyte_len(v: Column) -> Column:
    return F.greatest(F.lit(1), F.floor((bit_length(v) + 6) / 7)).cast("long")


def byte_len(v: Column) -> Column:
    return F.greatest(F.lit(1), F.floor((bit_length(v) + 7) / 8)).cast("long")


def word_index(i: Column, b: Column, lanes: int = 1) -> Column:
    """Word that value i of a block of width b begins in; with lanes, value i lies in lane i mod lanes."""
    if lanes == 1:
        return F.floor(i * b / 32).cast("int")
    return (F.floor(F.floor(i / lanes) * b / 32) * lanes + i % lanes).cast("int")


def word_shift(i: Column, b: Column, lanes: int = 1) -> Column:
    return ((i if lanes == 1 else F.floor(i / lanes)) * b % 32).cast("int")


def u32_ok(v: Column) -> Column:
    return v.isNotNull() & (v >= 0) & (v < LIMIT)


def split64(v: Column) -> tuple[Column, Column]:
    """High and low 32 bits of a 64-bit id."""
    return F.shiftrightunsigned(v, 32), v.bitwiseAND(F.lit(LIMIT - 1))


def join64(high: Column, low: Column) -> Column:
    return F.shiftleft(high, 32).bitwiseOR(low)
