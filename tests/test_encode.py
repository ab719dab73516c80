import random

import pytest
from pyspark.sql import functions as F

from bitplane.functions import metrics
from bitplane.functions.codecs import DecimalCodec, IntCodec
from bitplane.operators import aggregate, encode, skipping
from bitplane.operators.table import SlicedTable
from bitplane.plans import binding, planner
from bitplane.plans.predicates import And, In, Not, Or, between, columns, eq, gt, in_list, is_null, le, normalise, parse

LONG = IntCodec(sql="bigint")


def frame(spark, xs, files=1):
    return spark.createDataFrame([(i % files, i // files, x) for i, x in enumerate(xs)], "file_id long, row_index long, x long").coalesce(1).sortWithinPartitions("file_id", "row_index")


@pytest.mark.parametrize("n", [1, 63, 64, 65, 1023, 1024, 1025])
@pytest.mark.parametrize("bias", ["global", "block", "file"])
def test_sizes(spark, n, bias):
    rnd = random.Random(n)
    xs = [rnd.choice([None, rnd.randint(-50, 1000)]) for _ in range(n)]
    t = SlicedTable.from_df(frame(spark, xs), {"x": LONG}, bias=bias)
    assert [r.x for r in t.all().fetch("x", address=True).orderBy("row_index").collect()] == xs
    assert t.words.agg(F.sum(F.bit_count("live"))).first()[0] == n


@pytest.mark.parametrize("xs", [[None] * 70, [7] * 70, [0] * 3, [-(1 << 63), (1 << 63) - 1, 0, None], [1 << 31, (1 << 32) - 1, 0], list(range(2048))])
@pytest.mark.parametrize("bias", ["global", "block"])
def test_values(spark, xs, bias):
    t = SlicedTable.from_df(frame(spark, xs, files=1), {"x": LONG}, bias=bias)
    assert [r.x for r in t.all().fetch("x", address=True).orderBy("row_index").collect()] == xs
    assert t.where("x IS NULL").count().first()[0] == xs.count(None)
    assert t.where("x >= 7").count().first()[0] == sum(x is not None and x >= 7 for x in xs)


def test_engines_and_blocks_agree(spark):
    rnd = random.Random(4)
    xs = [rnd.choice([None, i * i % 977]) for i in range(3000)]
    df = frame(spark, xs, files=3)
    codecs = {"x": LONG}
    for bias in ("global", "block", "file"):
        m = encode.plan(df, codecs, bias)
        a, b = (sorted(encode.to_words(df, codecs, m, e).collect(), key=lambda r: r[:3]) for e in ("arrow", "catalyst"))
        assert a == b
        back = encode.from_blocks(encode.to_blocks(df, codecs, m), m)
        assert back.exceptAll(df).isEmpty() and df.exceptAll(back).isEmpty()


def test_empty_table(spark):
    df = frame(spark, [])
    t = SlicedTable.from_df(df, {"x": LONG})
    assert t.where("x > 3").count().first()[0] == 0
    assert t.where("x > 3").fetch("x").collect() == []


def test_planes_are_checked(spark):
    df = frame(spark, [1, 100])
    with pytest.raises(ValueError):
        encode.plan(df, {"x": LONG}, "none", widths={"x": 3})
    with pytest.raises(ValueError):
        encode.plan(frame(spark, [-1]), {"x": LONG}, "none")
    with pytest.raises(ValueError):
        encode.plan(df, {"x": LONG}, block_size=100)
    assert encode.plan(df, {"x": LONG}, "none", widths={"x": 32})["x"].planes == 32


def test_three_valued_logic(spark):
    rnd = random.Random(11)
    rows = [(0, i, rnd.choice([None, 0, 1, 2, 5]), rnd.choice([None, 0, 3, 4])) for i in range(200)]
    df = spark.createDataFrame(rows, "file_id long, row_index long, x long, y long")
    t = SlicedTable.from_df(df, {"x": LONG, "y": LONG})
    atoms = ["x > 1", "x = 0", "y <= 3", "y <> 0", "x IN (1, 5)", "y NOT IN (3)", "x IS NULL", "y IS NOT NULL", "x BETWEEN 1 AND 2", "NOT (x BETWEEN 1 AND 2)", "x NOT IN (1, NULL)"]

    def build(depth):
        if depth == 0:
            return rnd.choice(atoms)
        k = rnd.choice(["AND", "OR", "NOT"])
        return f"NOT ({build(depth - 1)})" if k == "NOT" else f"({build(depth - 1)}) {k} ({build(depth - 1)})"

    preds = atoms + [build(rnd.randint(1, 3)) for _ in range(25)]
    got = t.mask_each(preds).agg(*[F.coalesce(F.sum(F.bit_count(f"mask{i}")), F.lit(0)).alias(f"c{i}") for i in range(len(preds))]).first()
    want = df.agg(*[F.count_if(F.expr(p)).alias(f"c{i}") for i, p in enumerate(preds)]).first()
    assert list(got) == list(want)


def test_normal_form():
    p = Not(And((gt("a", 1), Or((eq("b", 2), Not(is_null("c")))))))
    n = normalise(p)
    assert isinstance(n, Or) and n.parts[0] == le("a", 1) and isinstance(n.parts[1], And)
    assert columns(p) == {"a", "b", "c"} and normalise(Not(Not(gt("a", 1)))) == gt("a", 1)
    assert parse("a > 1 AND NOT b IN (1, 2)") == And((gt("a", 1), Not(in_list("b", [1, 2]))))


def test_runs_of_constants(spark):
    df = frame(spark, list(range(100)))
    t = SlicedTable.from_df(df, {"x": LONG})
    node = binding.bind(in_list("x", [*range(10, 30), 50]), t.manifest)
    assert binding.passes(node, t.manifest) == 3 * t.manifest["x"].planes
    assert t.where(in_list("x", [])).count().first()[0] == 0
    assert t.where(~in_list("x", [*range(10, 30), 50])).count().first()[0] == 79


def test_aggregates(spark):
    xs = [random.Random(9).randint(-500, 500) for _ in range(777)]
    for bias in ("global", "block"):
        t = SlicedTable.from_df(frame(spark, xs), {"x": LONG}, bias=bias)
        sel = t.where("x > -100")
        ok = sorted(x for x in xs if x > -100)
        s = sel.summary("x").first()
        assert (s.n, int(s.sum_ord), s.min_ord, s.max_ord) == (len(ok), sum(ok), ok[0], ok[-1])
    t = SlicedTable.from_df(frame(spark, xs), {"x": LONG})
    sel = t.where("x > -100")
    assert [sel.kth("x", k) for k in (0, 10, len(ok) - 1, len(ok))] == [ok[0], ok[10], ok[-1], None]
    m = aggregate.second_moment(sel.masked, t.manifest["x"]).first()
    base = t.manifest["x"].base
    assert int(m.sum_squares_above) == sum((x - base) ** 2 for x in ok)
    none = t.where("x > 500").summary("x").first()
    assert none.n == 0 and none.sum_ord is None and none.max_ord is None


def test_zone_map_and_bloom(spark):
    t = SlicedTable.from_df(frame(spark, list(range(5000))), {"x": LONG}, bias="block")
    node = binding.bind(parse("x BETWEEN 2100 AND 2200"), t.manifest)
    kept = skipping.skipped(t.words, t.manifest, node).first()
    assert (kept.words, kept.kept) == (79, 16)
    t = SlicedTable.from_df(frame(spark, list(range(5000))), {"x": LONG}, bias="block", bloom=("x",))
    left = t.words.where(skipping.bloom(("set", "x", (4097, 99999), False), t.manifest)).select("block_id").distinct().collect()
    assert 4 in {r.block_id for r in left} and len(left) <= 3
    assert skipping.bloom(("or", [("cmp", "x", "eq", 5), ("cmp", "x", "gt", 5)]), t.manifest) is None


def test_long_lists(spark):
    xs = [None if i % 91 == 0 else i * 7 % 5003 for i in range(4000)]
    df = frame(spark, xs)
    wanted = [k * 11 % 6007 - 50 for k in range(700)]
    for bias in ("block", "global"):
        t = SlicedTable.from_df(df, {"x": LONG}, bias=bias)
        for negated in (False, True):
            p = In("x", tuple(wanted), negated)
            want = sum(x is not None and (x in set(wanted)) != negated for x in xs)
            for how in ({}, {"engine": "numpy"}, {"mode": "oblivious"}, {"in_strategy": "hash"}):
                assert t.where(p, **how).count().first()[0] == want
        assert t.where(In("x", (*wanted, None), True)).count().first()[0] == 0
    assert t.where(In("x", tuple(wanted[:40])), in_strategy="each").count().first()[0] == sum(x in set(wanted[:40]) for x in xs)


def test_groups_and_distinct_without_known_codes(spark):
    xs = [None if i % 50 == 0 else i * 13 % 4001 for i in range(3000)]
    t = SlicedTable.from_df(frame(spark, xs), {"x": LONG}, bias="block")
    kept = [x for x in xs if x is not None and x > 100]
    assert sorted(r.x for r in t.where("x > 100").distinct("x").collect()) == sorted(set(kept))
    got = {r.x: (r.n, int(r.sum_ord)) for r in t.where("x > 100").group_sum("x", "x").collect()}
    assert got == {k: (kept.count(k), kept.count(k) * k) for k in set(kept)}
    none = SlicedTable.from_df(frame(spark, []), {"x": LONG}).all()
    assert none.distinct("x").collect() == none.group_sum("x", "x").collect() == none.group_sum("x").collect() == []


def test_planner():
    assert planner.choose_representation(6) == "sliced" and planner.choose_representation(40) == "plain"
    assert planner.choose_representation(20, distinct=1000) == "dict" and planner.choose_representation(6, point_lookups=True) == "plain"
    assert not planner.should_encode(10, 2, 1, 1) and planner.should_encode(10, 2, 1, 10) and not planner.should_encode(10, 2, 3, 1e9)
    assert planner.in_strategy(6, 16) == "runs" and planner.in_strategy(17, 100) == "hash"


def test_conjunct_order_and_split(spark):
    df = spark.createDataFrame([(0, 0, 1, 100000)], "file_id long, row_index long, a long, b long")
    m = encode.plan(df.union(df.selectExpr("file_id", "row_index + 1", "a + 1", "b - 99999")), {"a": LONG, "b": LONG})
    p = And((gt("b", 5), gt("a", 1)))
    assert planner.order_conjuncts(p, m).parts[0].col == "a"
    mine, rest = planner.split(And((gt("a", 1), between("zz", 1, 2))), m)
    assert mine == gt("a", 1) and len(rest) == 1


def test_metrics():
    assert [metrics.compression_ratio(b) for b in (4, 8, 16)] == [8, 4, 2] and round(metrics.compression_ratio(6), 2) == 5.33
    assert metrics.block_bytes(1024, 4, 512, 16) == 16 + 512
    assert [round(metrics.bytes_per_value(b), 3) for b in (6, 17, 26)] == [0.75, 2.125, 3.25]
    assert [metrics.plane_passes("eq", 6), metrics.plane_passes("between", 6), metrics.plane_passes("in", 6, 16)] == [6, 12, 96]
    assert round(metrics.break_even(4022, 662, 60), 1) == 6.7 and round(metrics.break_even(9932, 682, 158), 1) == 19.0
    assert metrics.total_cost(7, 4022, 60) < 7 * 662 and metrics.total_cost(6, 4022, 60) > 6 * 662
    assert metrics.compound_ops([6, 17], 64) == 24 and metrics.beats_scalar(32, 128) and not metrics.beats_scalar(64, 64)
    mean, half = metrics.mean_ci([1.0, 2.0, 3.0, 4.0, 5.0])
    assert mean == 3 and round(half, 2) == 6.09
    # Textbook values.
    for degrees, level, t in ((6, 0.999, 5.959), (4, 0.999, 8.610), (9, 0.999, 4.781), (1, 0.95, 12.706), (9, 0.95, 2.262), (6, 0.95, 2.447), (29, 0.95, 2.045), (200, 0.95, 1.972)):
        assert round(metrics.t_quantile(degrees, level), 3) == t
    e = metrics.economics(1e11, 4, 250, 1.0)
    assert e["gb"] == 400 and e["nodes"] == 2 and e["usd_year"] == 4000


def test_decimal_cents(spark):
    df = spark.createDataFrame([(0, i, x) for i, x in enumerate([0.07, 1.1, -2.35, None, 1e6 + 0.01])], "file_id long, row_index long, x double")
    t = SlicedTable.from_df(df, {"x": DecimalCodec(scale=2)}, bias="block")
    assert [None if r.x is None else float(r.x) for r in t.all().fetch("x", address=True).orderBy("row_index").collect()] == [0.07, 1.1, -2.35, None, 1000000.01]
    assert t.where("x = 1.1").count().first()[0] == 1
