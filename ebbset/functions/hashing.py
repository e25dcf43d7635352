"""Hash expressions: multiply-add-shift, sampling levels, ids. All native, and small enough never to overflow a long."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def key_of(text: Column, digits: int = 15) -> Column:
    """A whole number from the first hexadecimal digits of a text's MD5: 15 digits as identity, 7 as hash input."""
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def hash_input(item: Column, mode: str = "scrambled") -> Column:
    """28 bits to hash. Pairwise independent hashes of consecutive ids are too regular for occupancy estimates, so ids
    are scrambled by default; raw takes them as they are (below 2**31)."""
    return key_of(item.cast("string"), 7) if mode == "scrambled" else item.cast("long")


def shift_hash(x: Column, ab: tuple[int, int], bits: int) -> Column:
    """Multiply-add-shift in a 32-bit word to that many bits."""
    a, b = ab
    return F.shiftrightunsigned((F.lit(a).cast("long") * x + F.lit(b).cast("long")).bitwiseAND(F.lit((1 << 32) - 1)), 32 - bits)


def level_of(h: Column, log_m: int) -> Column:
    """Position of the lowest one bit, counted from 1; zero falls to the last level."""
    return F.when(h == 0, F.lit(log_m)).otherwise(F.bit_count(h.bitwiseAND(-h) - 1) + 1).cast("int")


PRIME = (1 << 31) - 1


def coefficient(x: Column, ab: tuple[int, int]) -> Column:
    """A field element from 1 to PRIME - 1 per item, for linear sketches."""
    return F.pmod(shift_hash(x, ab, 31), F.lit(PRIME - 1)) + 1


def field_hash(x: Column, ab: tuple[int, int]) -> Column:
    """(a x + b) modulo 2**61 - 1, for items below 2**31: a wider family, at the price of decimal arithmetic."""
    a, b = ab
    whole = F.lit(str(a)).cast("decimal(20,0)") * x.cast("decimal(10,0)") + F.lit(str(b)).cast("decimal(20,0)")
    return F.pmod(whole, F.lit(str((1 << 61) - 1)).cast("decimal(20,0)")).cast("long")
