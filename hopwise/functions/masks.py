"""Sets of sources as bits of a BIGINT: all built-in expressions, inside generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bit(position: Column | str) -> Column:
    position = F.col(position) if isinstance(position, str) else position
    return F.call_function("shiftleft", F.lit(1).cast("long"), position.cast("int"))


def union(a: Column, b: Column) -> Column:
    return a.bitwiseOR(b)


def minus(a: Column, b: Column) -> Column:
    return a.bitwiseAND(F.bitwise_not(b))


def meets(a: Column, b: Column) -> Column:
    return a.bitwiseAND(b) != 0


def size(a: Column) -> Column:
    return F.bit_count(a)


def has(mask: Column, position: Column) -> Column:
    return meets(mask, bit(position))


def full(width: int) -> int:
    """The mask of ``width`` sources, as a signed 64-bit integer."""
    return -1 if width == 64 else (1 << width) - 1


def record_distance(base: Column, masks: Column, position: Column) -> Column:
    """Distance of the source at ``position``: the base plus the offset of the mask that holds it; null if none does."""
    at = F.transform(masks, lambda m, i: F.when(has(m, position), i))
    return base + F.array_min(at)


def once(value: Column, use) -> Column:
    """``use(value)`` with the value bound to a lambda's variable, so that it is worked out once however often it is used."""
    return F.get(F.transform(F.array(value), use), F.lit(0))
