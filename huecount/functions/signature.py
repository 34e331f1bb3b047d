"""Sets of colours as bitmaps in a BIGINT."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bit(color: Column) -> Column:
    """The set of one colour (0-based)."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), color.cast("int"))


def full(k: int) -> int:
    return (1 << k) - 1


def size(sig: Column) -> Column:
    return F.bit_count(sig)


def has_not(sig: Column, one: Column) -> Column:
    return sig.bitwiseAND(one) == 0


def disjoint_except(a: Column, b: Column, shared: Column) -> Column:
    """Two sets meet in exactly the shared colours."""
    return a.bitwiseAND(b) == shared


def union(a: Column, b: Column) -> Column:
    return a.bitwiseOR(b)
