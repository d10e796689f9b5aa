"""Packing of small unsigned codes into long integers, and of two four-bit codes into a byte."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from vecspark.functions.vectors import total


def pack_bits(codes: list[Column], b: int) -> Column:
    """Codes of b bits, the first in the lowest bits; len(codes) * b must not pass 63 (64 wraps to the sign)."""
    out = codes[0].cast("long")
    for j, c in enumerate(codes[1:], 1):
        out = out.bitwiseOR(F.shiftleft(c.cast("long"), j * b))
    return out


def unpack_bits(packed: Column, j: int, b: int) -> Column:
    return F.shiftrightunsigned(packed, j * b).bitwiseAND((1 << b) - 1)


def pack_nibbles(high: Column, low: Column) -> Column:
    return high * 16 + low


def high_nibble(byte: Column) -> Column:
    return F.shiftright(byte, 4).bitwiseAND(15)


def low_nibble(byte: Column) -> Column:
    return byte.bitwiseAND(15)


def group_id(codes: list[Column], low_bits: int = 4) -> Column:
    """One number for the tuple of the codes' high parts: the first is the most significant."""
    width = 8 - low_bits
    return total([F.shiftleft(F.shiftright(c.cast("long"), low_bits), width * (len(codes) - 1 - j)) for j, c in enumerate(codes)])


def interleave(values: list[Column], bits: int) -> Column:
    """Z-order of non-negative integers, most significant bits first, in one long."""
    terms = []
    for bit in range(bits):
        for j, v in enumerate(values):
            place = bit * len(values) + (len(values) - 1 - j)
            terms.append(F.shiftleft(F.shiftright(v.cast("long"), bit).bitwiseAND(1), place))
    return total(terms)
