"""Every value against every constant, in all engines, and the worked example."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitplane.functions.codecs import IntCodec
from bitplane.operators.table import SlicedTable
from bitplane.plans import binding, kernels
from bitplane.plans.predicates import Between, Cmp, Not, in_list, parse
from bitplane.plans.spec import ColumnSpec, Manifest

OPS = {"eq": np.equal, "ne": np.not_equal, "gt": np.greater, "ge": np.greater_equal, "lt": np.less, "le": np.less_equal}


def words(xs, spec):
    n = -(-len(xs) // 64) * 64
    bits = np.zeros(n, np.uint64)
    bits[: len(xs)] = np.array(xs, np.int64) - spec.base
    out = {"live": np.packbits(np.arange(n) < len(xs), bitorder="little").view(np.int64)}
    for j in range(spec.planes):
        out[spec.plane(j)] = np.packbits((bits >> np.uint64(j) & np.uint64(1)).astype(np.uint8), bitorder="little").view(np.int64)
    return out


def bits(mask, n):
    return np.unpackbits(np.ascontiguousarray(mask).view(np.uint8), bitorder="little")[:n].astype(bool)


@pytest.mark.parametrize("b", [1, 2, 3, 5, 6])
@pytest.mark.parametrize("kernel", ["lsb", "msb_two_mask"])
@pytest.mark.parametrize("lanes", [64, 32, 8])
def test_all_values_all_constants(b, kernel, lanes):
    xs = np.arange(1 << b)
    spec = ColumnSpec("x", IntCodec(), "none", b, 0, 0, (1 << b) - 1, has_nulls=False)
    m, cols = Manifest((spec,)), words(xs, spec)
    for op, test in OPS.items():
        for c in range(-2, (1 << b) + 2):
            node = binding.bind(Cmp(op, "x", c), m)
            got = kernels.numpy_mask(node, m, lambda n: cols.get(n), kernel, lanes)
            assert np.array_equal(bits(got, len(xs)), test(xs, c)), (op, c)


def test_constants_beyond_the_width_without_statistics():
    xs = np.arange(8)
    spec = ColumnSpec("x", IntCodec(), "none", 3, has_nulls=False)
    m, cols = Manifest((spec,)), words(xs, spec)
    for op, test in OPS.items():
        for c in (-9, -1, 0, 7, 8, 1000, 1 << 40):
            got = kernels.numpy_mask(("cmp", "x", op, c), m, lambda n: cols.get(n))
            assert np.array_equal(bits(got, 8), test(xs, c)), (op, c)


def test_worked_example(spark):
    rows = [(0, i, x) for i, x in enumerate([5, 0, 3, 7, None, 2, 6, 4])]
    df = spark.createDataFrame(rows, "file_id long, row_index long, x int").coalesce(1)
    t = SlicedTable.from_df(df, {"x": IntCodec()}, bias="none")
    w = t.words.first()
    assert (w["x__p0"], w["x__p1"], w["x__p2"], w["x__v"], w["live"]) == (0x0D, 0x6C, 0xC9, 0xEF, 0xFF)
    ids = lambda p: sorted(r.row_index for r in t.where(p).row_ids().collect())
    assert ids("x > 3") == [0, 3, 6, 7]
    assert ids("x >= 3") == [0, 2, 3, 6, 7]
    assert ids("NOT (x > 3)") == [1, 2, 5]
    assert t.where("x > 3").summary("x").first()["sum_ord"] == 22


@pytest.mark.parametrize("bias", ["none", "global", "block", "file"])
@pytest.mark.parametrize("mode", ["skip", "oblivious"])
def test_generated_code_over_all_constants(spark, bias, mode):
    xs = [3, 4, 9, 12, 12, 7, None, 3, 10] * 9
    df = spark.createDataFrame([(1, i, x) for i, x in enumerate(xs)], "file_id long, row_index long, x long")
    t = SlicedTable.from_df(df, {"x": IntCodec(sql="bigint")}, bias=bias, block_size=64)
    for c in (-1, 2, 3, 7, 8, 12, 13, 99):
        preds = [Cmp(op, "x", c) for op in OPS] + [Between("x", c, 10), Not(Between("x", 4, c)), in_list("x", [c, 9, 77])]
        masks = t.words.select("live", *[kernels.catalyst(binding.bind(p, t.manifest), t.manifest, mode).alias(f"m{i}") for i, p in enumerate(preds)])
        got = masks.agg(*[F.sum(F.bit_count(f"m{i}")).alias(f"m{i}") for i in range(len(preds))]).first()
        ok = [x for x in xs if x is not None]
        want = [sum(bool(OPS[op](x, c)) for x in ok) for op in OPS] + [sum(c <= x <= 10 for x in ok), sum(not 4 <= x <= c for x in ok), sum(x in (c, 9, 77) for x in ok)]
        assert list(got) == want, c


def test_expression_size_does_not_depend_on_the_constant():
    spec = ColumnSpec("x", IntCodec(), "none", 6, 0, 0, 63, has_nulls=False)
    m = Manifest((spec,))
    assert {binding.passes(binding.bind(Cmp("gt", "x", c), m), m) for c in range(0, 63)} == {6}
    assert binding.passes(binding.bind(Between("x", 10, 19), m), m) == 12
    assert binding.passes(binding.bind(Between("x", 0, 19), m), m) == 6
    assert binding.passes(binding.bind(in_list("x", range(0, 62, 4)), m, "each"), m) == 96


def test_array_engine_agrees(spark):
    df = spark.range(300).selectExpr("1L as file_id", "id as row_index", "id * 7 % 53 as x")
    t = SlicedTable.from_df(df, {"x": IntCodec(sql="bigint")})
    for p in ("x > 20", "x = 7", "x BETWEEN 5 AND 30", "x <> 3", "NOT (x IN (1, 2, 3, 9))"):
        assert t.where(p).count().first() == t.where(p, engine="array").count().first() == t.where(p, engine="numpy").count().first() == (df.where(p).count(),)


def test_parse_rejects_nonsense():
    for text in ("x >", "x IN ()", "x BETWEEN 1", "(x = 1", "x = 1 y = 2", "x ~ 3"):
        with pytest.raises(ValueError):
            parse(text)
