"""Lengths of codes as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bit_length(n: Column) -> Column:
    """Bits of a number that is not negative, 0 for 0; exact, as no logarithm is taken."""
    return F.when(n == 0, 0).otherwise(F.length(F.bin(n)))


def exp_golomb_bits(n: Column, k: int) -> Column:
    """Length of the order-k code of n: 2 * floor(log2((n >> k) + 1)) + 1 + k."""
    return (bit_length(F.shiftright(n, k) + 1) - 1) * 2 + 1 + k


def packed_bits(most: Column, count: Column) -> Column:
    """Fixed-width packing."""
    return bit_length(most) * count
