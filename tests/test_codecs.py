import datetime as dt
import decimal
import math

import pytest
from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from bitplane.functions.codecs import DateCodec, DecimalCodec, DictCodec, DoubleCodec, IntCodec, TimestampCodec
from bitplane.operators.table import SlicedTable
from bitplane.plans.predicates import Cmp


@given(st.floats(allow_nan=False), st.floats(allow_nan=False))
def test_double_bits_keep_order(a, b):
    x, y = DoubleCodec.bits(a), DoubleCodec.bits(b)
    assert (x < y) == (a < b) and (x == y) == (a == b)


def test_double_specials():
    order = [-math.inf, -1e308, -5e-324, 0.0, 5e-324, 1.0, math.inf, math.nan]
    got = [DoubleCodec.bits(x) for x in order]
    assert got == sorted(set(got)) and DoubleCodec.bits(-0.0) == 0


def test_double_column(spark):
    xs = [1.5, -0.0, 0.0, -3.25, math.inf, -math.inf, math.nan, None, 5e-324, -1e308]
    df = spark.createDataFrame([(0, i, x) for i, x in enumerate(xs)], "file_id long, row_index long, x double")
    t = SlicedTable.from_df(df, {"x": DoubleCodec()})
    assert t.manifest["x"].planes == 64
    back = [r.x for r in t.all().fetch("x", address=True).orderBy("row_index").collect()]
    assert [repr(b) for b in back] == [repr(x + 0.0) if x is not None else "None" for x in xs]
    for op, sql in (("gt", ">"), ("ge", ">="), ("lt", "<"), ("le", "<="), ("eq", "="), ("ne", "<>")):
        for c in (0.0, -3.25, 1.0, math.inf, math.nan):
            lit = "double('NaN')" if c != c else "double('Infinity')" if c == math.inf else f"double({c})"
            assert t.where(Cmp(op, "x", c)).count().first()[0] == df.where(f"x {sql} {lit}").count(), (op, c)


def test_fractional_constants():
    c = IntCodec()
    assert c.bound("gt", 24.5) == ("gt", 24) and c.bound("ge", 24.5) == ("gt", 24)
    assert c.bound("lt", 24.5) == ("le", 24) and c.bound("eq", 24.5) == ("none", None) and c.bound("ne", 24.5) == ("all", None)
    assert c.bound("lt", -0.5) == ("le", -1)
    d = DecimalCodec(scale=2)
    assert d.bound("eq", 10.25) == ("eq", 1025) and d.bound("gt", 10.255) == ("gt", 1025) and d.bound("eq", decimal.Decimal("0.07")) == ("eq", 7)


def test_dates_and_times():
    assert DateCodec().bound("ge", "1970-01-02") == ("ge", 1)
    assert DateCodec().bound("lt", dt.date(1969, 12, 31)) == ("lt", -1)
    assert TimestampCodec().bound("eq", "1970-01-01 00:00:01.000002") == ("eq", 1_000_002)


def test_dictionary_ranges():
    d = DictCodec(values=("a", "b", "bb", "c"))
    assert d.bound("gt", "b") == ("ge", 2) and d.bound("ge", "ba") == ("ge", 2) and d.bound("le", "b") == ("lt", 2)
    assert d.bound("eq", "zz") == ("none", None) and d.bound("ne", "zz") == ("all", None)
    with pytest.raises(ValueError):
        DictCodec(values=("b", "a"), ordered=False).bound("lt", "b")


def test_timestamp_column(spark):
    xs = [dt.datetime(1969, 12, 31, 23, 59, 59, 999999), dt.datetime(2024, 2, 29, 1, 2, 3, 4), None]
    df = spark.createDataFrame([(0, i, x) for i, x in enumerate(xs)], "file_id long, row_index long, x timestamp_ntz")
    t = SlicedTable.from_df(df, {"x": TimestampCodec()}, bias="block")
    assert [r.x for r in t.all().fetch("x", address=True).orderBy("row_index").collect()] == xs
    assert t.where("x < TIMESTAMP '1970-01-01 00:00:00'").count().first()[0] == 1


def test_unicode_and_empty_strings(spark):
    xs = ["", "a", "é", "中", "z", None]
    df = spark.createDataFrame([(0, i, x) for i, x in enumerate(xs)], "file_id long, row_index long, s string")
    from bitplane.operators import dictionary

    t = SlicedTable.from_df(df, {"s": dictionary.build(df, "s")})
    for p in ("s = ''", "s > 'a'", "s <= 'é'", "s LIKE '%'", "s NOT LIKE 'a%'", "s IN ('中', 'q')", "s IS NULL"):
        assert t.where(p).count().first()[0] == df.where(p).count(), p
    with pytest.raises(dictionary.DictionaryTooLarge):
        dictionary.build(df, "s", most=2)
    arrival = dictionary.build(df.where(F.col("row_index") != 1), "s", order="arrival")
    assert arrival.values == ("", "é", "中", "z")
