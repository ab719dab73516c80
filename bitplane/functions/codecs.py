"""Order-preserving maps from SQL types to BIGINT ordinals.

``ordinal`` maps a column, ``value`` maps back, ``bound`` maps a constant of a
predicate: it gives (operator, ordinal) with the same rows, where a constant
falls between ordinals, or a verdict for constants outside the type's domain.
"""

from __future__ import annotations

import dataclasses
import datetime as dt
import decimal
import math
import struct
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

EPOCH = dt.datetime(1970, 1, 1)


@dataclasses.dataclass(frozen=True)
class Codec:
    linear: bool = True  # ordinals differ as values do, so sums of planes are sums of values

    def ordinal(self, c: Column) -> Column:
        return c.cast("long")

    def value(self, c: Column) -> Column:
        return c

    def constant(self, x: Any) -> tuple[int, bool]:
        """Ordinal at or below the constant, and whether it is exact."""
        low = math.floor(x)
        return int(low), low == x

    def bound(self, op: str, x: Any) -> tuple[str, int | None]:
        """(operator, ordinal); ordinal None means the operator alone decides ("all" or "none" of the non-null rows)."""
        if isinstance(x, float) and math.isnan(x):  # SQL order puts NaN above everything
            return {"lt": "all", "le": "all", "ne": "all"}.get(op, "none"), None
        if isinstance(x, float) and math.isinf(x):
            above = x > 0
            return ("all" if op == "ne" or (op in ("lt", "le")) == above and op != "eq" else "none"), None
        k, exact = self.constant(x)
        if exact:
            return op, k
        return {"eq": ("none", None), "ne": ("all", None), "gt": ("gt", k), "ge": ("gt", k), "lt": ("le", k), "le": ("le", k)}[op]


@dataclasses.dataclass(frozen=True)
class IntCodec(Codec):
    """Integers of any width, and doubles that hold whole numbers."""

    sql: str = "int"

    def value(self, c: Column) -> Column:
        return c.cast(self.sql)


@dataclasses.dataclass(frozen=True)
class BoolCodec(Codec):
    def ordinal(self, c: Column) -> Column:
        return c.cast("int").cast("long")

    def value(self, c: Column) -> Column:
        return c != 0


@dataclasses.dataclass(frozen=True)
class DateCodec(Codec):
    linear: bool = False

    def ordinal(self, c: Column) -> Column:
        return F.unix_date(c.cast("date")).cast("long")

    def value(self, c: Column) -> Column:
        return F.date_from_unix_date(c.cast("int"))

    def constant(self, x: Any) -> tuple[int, bool]:
        x = dt.date.fromisoformat(x) if isinstance(x, str) else x
        return (x.date() if isinstance(x, dt.datetime) else x).toordinal() - EPOCH.toordinal(), True


@dataclasses.dataclass(frozen=True)
class TimestampCodec(Codec):
    """Microseconds since the epoch, without a zone."""

    linear: bool = False

    def ordinal(self, c: Column) -> Column:
        return _micros(c)

    def value(self, c: Column) -> Column:
        return (F.to_timestamp_ntz(F.lit("1970-01-01 00:00:00")) + F.make_dt_interval(secs=(c / F.lit(1_000_000).cast("decimal(20,0)")).cast("decimal(18,6)"))).cast("timestamp_ntz")

    def constant(self, x: Any) -> tuple[int, bool]:
        x = dt.datetime.fromisoformat(x) if isinstance(x, str) else x
        x = dt.datetime(x.year, x.month, x.day) if type(x) is dt.date else x
        d = x - EPOCH
        return (d.days * 86_400 + d.seconds) * 1_000_000 + d.microseconds, True


def _micros(c: Column) -> Column:
    day = F.unix_date(c.cast("date")).cast("long")
    rest = (F.hour(c) * 3600 + F.minute(c) * 60).cast("long") * 1_000_000 + (F.extract(F.lit("SECOND"), c) * 1_000_000).cast("long")
    return day * 86_400_000_000 + rest


@dataclasses.dataclass(frozen=True)
class DecimalCodec(Codec):
    """Fixed point: ordinals are units of 10**-scale.  Doubles are rounded, never floored."""

    scale: int = 2

    def ordinal(self, c: Column) -> Column:
        return F.round(c * F.lit(10**self.scale)).cast("long")

    def value(self, c: Column) -> Column:
        return (c.cast("decimal(20,0)") / F.lit(10**self.scale).cast("decimal(20,0)")).cast(f"decimal(20,{self.scale})")

    def constant(self, x: Any) -> tuple[int, bool]:
        scaled = decimal.Decimal(repr(x) if isinstance(x, float) else x) * 10**self.scale
        low = int(scaled.to_integral_value(decimal.ROUND_FLOOR))
        return low, low == scaled


@dataclasses.dataclass(frozen=True)
class DoubleCodec(Codec):
    """IEEE bits in numeric order as signed BIGINT: -0.0 equals 0.0, NaN is the greatest value.

    ``ordinal`` needs raw bits and so goes through Arrow; see operators.encode.
    """

    linear: bool = False

    @staticmethod
    def bits(x: float) -> int:
        if math.isnan(x):
            return 0x7FF8000000000000
        raw = struct.unpack("<q", struct.pack("<d", x + 0.0))[0]
        return raw if raw >= 0 else -(raw & 0x7FFFFFFFFFFFFFFF)

    def ordinal(self, c: Column) -> Column:
        return ordered_bits()(c.cast("double"))

    def value(self, c: Column) -> Column:
        return from_ordered_bits()(c)

    def bound(self, op: str, x: Any) -> tuple[str, int | None]:
        return op, self.bits(float(x))


def ordered_bits():
    """Arrow functions, as pandas cannot tell null from NaN."""

    @F.arrow_udf("long")
    def run(c: pa.Array) -> pa.Array:
        x = c.fill_null(0.0).to_numpy(zero_copy_only=False) + 0.0
        raw = np.where(np.isnan(x), np.int64(0x7FF8000000000000), x.view(np.int64))
        return pa.array(np.where(raw >= 0, raw, -(raw & np.int64(0x7FFFFFFFFFFFFFFF))), mask=c.is_null().to_numpy(zero_copy_only=False))

    return run


def from_ordered_bits():
    @F.arrow_udf("double")
    def run(c: pa.Array) -> pa.Array:
        k = c.fill_null(0).to_numpy(zero_copy_only=False)
        raw = np.where(k >= 0, k, (-k) | np.int64(-0x8000000000000000))
        return pa.array(raw.view(np.float64), mask=c.is_null().to_numpy(zero_copy_only=False))

    return run


@dataclasses.dataclass(frozen=True)
class DictCodec(Codec):
    """Strings by code: position in the sorted (or arrival-ordered) list of distinct values."""

    values: tuple[str, ...] = ()
    ordered: bool = True
    linear: bool = False

    def ordinal(self, c: Column) -> Column:
        # A literal map is looked up by hash inside generated code; its size is checked where it is built.
        table = F.map_from_arrays(F.array(*map(F.lit, self.values)), F.array(*[F.lit(i).cast("long") for i in range(len(self.values))]))
        return table[c] if self.values else F.lit(None).cast("long")

    def value(self, c: Column) -> Column:
        return F.get(F.array(*map(F.lit, self.values)), c.cast("int")) if self.values else F.lit(None).cast("string")

    def bound(self, op: str, x: Any) -> tuple[str, int | None]:
        if op in ("eq", "ne"):
            code = self.values.index(x) if x in self.values else None
            return (op, code) if code is not None else ({"eq": "none", "ne": "all"}[op], None)
        if not self.ordered:
            raise ValueError("order predicates need a sorted dictionary")
        below = sum(v.encode() < x.encode() for v in self.values)
        return {"lt": ("lt", below), "ge": ("ge", below), "gt": ("ge", below + (x in self.values)), "le": ("lt", below + (x in self.values))}[op]

    def matching(self, test) -> list[int]:
        return [i for i, v in enumerate(self.values) if test(v)]
