"""Expressions that Spark and other SQL engines compute alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

HASH_SPACE = float(1 << 32)


def hash32(text: Column) -> Column:
    """First 32 bits of md5 as a number from 0 to 2^32 - 1; null for null."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def draw_order(part: Column, seed: int) -> Column:
    """A reproducible arithmetic shuffle of partition ids; ties go to the lower id."""
    return F.pmod(part * F.lit(7919) + F.lit(seed * 104729), F.lit(10007))


def zipf_like(key: Column, kinds: int = 25) -> Column:
    """A skewed group number from 1 to ``kinds`` out of a uniform key."""
    return F.floor(F.exp(F.ln(F.lit(float(kinds + 1))) * (key % 997) / F.lit(997.0))).cast("int")


def signed_log(x: Column) -> Column:
    """Keeps the sign, shrinks heavy tails."""
    return F.signum(x) * F.log1p(F.abs(x))
