"""Column expressions over 64-row words."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 64
ALL, NONE = -1, 0


def lit(x: int) -> Column:
    return F.lit(x).cast("long")


def shl(x: Column, by: Column) -> Column:
    return F.call_function("shiftleft", x, by)


def bit(word: Column, pos: Column) -> Column:
    """0 or 1 as BIGINT."""
    return F.getbit(word, pos).cast("long")


def bit_width(x: Column, most: int = 63) -> Column:
    """Planes a non-negative BIGINT needs, at least 1; by integer tests, never by logarithms."""
    out = F.lit(1)
    for j in range(1, most):
        out = F.when(F.shiftrightunsigned(x, j) != 0, F.lit(j + 1)).otherwise(out) if j == 1 else F.greatest(out, F.when(F.shiftrightunsigned(x, j) != 0, F.lit(j + 1)).otherwise(F.lit(1)))
    return out


def popcount(mask: Column) -> Column:
    return F.bit_count(mask).cast("long")


def positions(mask: Column) -> Column:
    """Ascending positions of the set bits."""
    return F.filter(F.sequence(F.lit(0), F.lit(WORD - 1)), lambda i: F.getbit(mask, i) == 1)


def balanced(merge: Callable[[Column, Column], Column], parts: list[Column]) -> Column:
    """A tree as deep as the logarithm of the parts: long lists do not exhaust the planner's stack."""
    while len(parts) > 1:
        parts = [merge(*parts[i : i + 2]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return parts[0]


def any_of(masks: list[Column]) -> Column:
    return balanced(lambda a, b: a.bitwiseOR(b), masks) if masks else lit(NONE)


def all_of(masks: list[Column]) -> Column:
    return balanced(lambda a, b: a.bitwiseAND(b), masks) if masks else lit(ALL)
