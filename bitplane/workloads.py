"""The experiment workloads on the given tables, each with the SQL that checks it."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import metrics
from .functions.codecs import BoolCodec, Codec, DateCodec, DecimalCodec, DoubleCodec, IntCodec, TimestampCodec
from .operators import aggregate, baselines, dictionary, encode, joins, relational, select, skipping
from .operators.table import SlicedTable
from .plans import binding, planner
from .plans.predicates import parse
from .sources import sliced as store
from .sources.sliced import scratch
from .sources.tables import FILE, ROW, load, load_addressed
from .streaming import events as streams

Query = Callable[[SparkSession, str], DataFrame]

QUANTITY, CENTS, DAYS, KEY = IntCodec(sql="int"), DecimalCodec(scale=2), DateCodec(), IntCodec(sql="bigint")
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def sliced(spark: SparkSession, d: str, table: str, codecs: dict[str, Codec], strings: tuple[str, ...] = (), **how) -> SlicedTable:
    """Encodes the named columns of a table; ``strings`` get sorted dictionaries."""
    names = [*codecs, *strings]
    df = load_addressed(spark, d, table, names)
    codecs = dict(codecs) | {c: dictionary.build(df, c) for c in strings}
    return SlicedTable.from_df(df, codecs, **how)


LINEITEM = {"l_quantity": QUANTITY, "l_extendedprice": CENTS, "l_orderkey": KEY}


def labelled(spark: SparkSession, d: str) -> SlicedTable:
    """documents with their labels where there are any: the nullable table."""
    docs = load_addressed(spark, d, "documents", ["doc_id"])
    df = docs.join(load(spark, d, "labels"), "doc_id", "left").repartitionByRange(FILE, ROW).sortWithinPartitions(FILE, ROW)
    return SlicedTable.from_df(df, {"doc_id": KEY, "quality": QUANTITY, "toxic": QUANTITY}, bias="global")


# --- predicates: the selected rows' number and the sums of their keys and prices

PREDICATES = {
    "eq": "l_quantity = 25", "ne": "l_quantity <> 25", "gt": "l_quantity > 25", "ge": "l_quantity >= 25", "lt": "l_quantity < 25", "le": "l_quantity <= 25",
    "between": "l_quantity BETWEEN 10 AND 19", "between_lo_min": "l_quantity BETWEEN 1 AND 10", "between_empty": "l_quantity BETWEEN 19 AND 10", "not_between": "l_quantity NOT BETWEEN 10 AND 19",
    "in4": "l_quantity IN (3, 17, 30, 44)", "in16": "l_quantity IN (1, 4, 7, 10, 13, 16, 19, 22, 25, 28, 31, 34, 37, 40, 43, 46)", "not_in": "l_quantity NOT IN (3, 17, 30, 44, 77)",
    "and": "l_quantity > 12 AND l_extendedprice BETWEEN 5000 AND 80000", "or": "l_quantity > 45 OR l_extendedprice < 3000.5", "not": "NOT (l_quantity > 12 OR l_extendedprice > 80000)",
    "nested": "NOT (l_quantity IN (5, 6, 7) AND NOT (l_extendedprice > 50000)) AND (l_orderkey < 9000 OR l_quantity = 50)",
    "fraction": "l_quantity > 24.5", "beyond": "l_quantity < 1000", "below": "l_quantity <= -5",
}

ROWS_SQL = "SELECT count(*)::BIGINT AS n, sum(l_orderkey)::BIGINT AS sum_key, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS sum_cents FROM lineitem WHERE {}"


def totals(rows: DataFrame) -> DataFrame:
    return rows.agg(F.count(F.lit(1)).alias("n"), F.sum("l_orderkey").alias("sum_key"), F.sum((F.col("l_extendedprice") * 100).cast("long")).alias("sum_cents"))


def predicate(text: str, **how) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        table = sliced(spark, d, "lineitem", LINEITEM, bias=how.get("bias", "global"), widths=how.get("widths"))
        return totals(table.where(text, **{k: v for k, v in how.items() if k not in ("bias", "widths")}).fetch("l_orderkey", "l_extendedprice"))

    return run


for name, text in PREDICATES.items():
    add(f"pred_{name}", predicate(text), ROWS_SQL.format(text))
for name in ("between", "nested", "in16"):
    add(f"engine_numpy_{name}", predicate(PREDICATES[name], engine="numpy"), ROWS_SQL.format(PREDICATES[name]))
    add(f"engine_array_{name}", predicate(PREDICATES[name], engine="array"), ROWS_SQL.format(PREDICATES[name]))
    add(f"bias_block_{name}", predicate(PREDICATES[name], bias="block"), ROWS_SQL.format(PREDICATES[name]))
    add(f"bias_file_{name}", predicate(PREDICATES[name], bias="file"), ROWS_SQL.format(PREDICATES[name]))
    add(f"oblivious_{name}", predicate(PREDICATES[name], mode="oblivious"), ROWS_SQL.format(PREDICATES[name]))
add("kernel_two_mask", predicate(PREDICATES["nested"], engine="numpy", kernel="msb_two_mask"), ROWS_SQL.format(PREDICATES["nested"]))
add("kernel_lanes_32", predicate(PREDICATES["nested"], engine="numpy", lane_bits=32), ROWS_SQL.format(PREDICATES["nested"]))
add("in_by_equality", predicate(PREDICATES["in16"], in_strategy="each"), ROWS_SQL.format(PREDICATES["in16"]))

MANY = ", ".join(str(k * 13 % 20011) for k in range(1000))
add("pred_in1000", predicate(f"l_orderkey IN ({MANY})"), ROWS_SQL.format(f"l_orderkey IN ({MANY})"))
add("pred_not_in1000", predicate(f"l_orderkey NOT IN ({MANY}) AND l_quantity > 25"), ROWS_SQL.format(f"l_orderkey NOT IN ({MANY}) AND l_quantity > 25"))
add("engine_numpy_in1000", predicate(f"l_orderkey IN ({MANY})", engine="numpy", bias="block"), ROWS_SQL.format(f"l_orderkey IN ({MANY})"))
add("in_by_equality_64", predicate(f"l_orderkey IN ({', '.join(str(23 * k) for k in range(64))})", in_strategy="each"), ROWS_SQL.format("l_orderkey % 23 = 0 AND l_orderkey < 1472"))
add("in_by_hash", predicate(PREDICATES["in16"], in_strategy="hash", bias="block"), ROWS_SQL.format(PREDICATES["in16"]))
add("widths_fixed_32", predicate(PREDICATES["and"], widths={c: 32 for c in LINEITEM}), ROWS_SQL.format(PREDICATES["and"]))
add("widths_fixed_64", predicate(PREDICATES["nested"], bias="none", widths={c: 64 for c in LINEITEM}), ROWS_SQL.format(PREDICATES["nested"]))

NULLABLE = {
    "is_null": "quality IS NULL", "not_null": "quality IS NOT NULL", "gt": "quality > 0", "not_gt": "NOT (quality > 0)", "not_or": "NOT (quality = 0 OR toxic = 1)",
    "not_and": "NOT (quality = 1 AND toxic = 0)", "not_in": "quality NOT IN (0)", "or_null": "quality = 1 OR toxic IS NULL",
}
for name, text in NULLABLE.items():
    add(
        f"null_{name}", lambda spark, d, text=text: labelled(spark, d).where(text).fetch("doc_id").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("sum_id")),
        f"SELECT count(*)::BIGINT AS n, sum(doc_id)::BIGINT AS sum_id FROM documents LEFT JOIN labels USING (doc_id) WHERE {text}",
    )


# --- encodings

def round_trip(table: str, col: str, codec: Codec | None, show: str, **how) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        t = sliced(spark, d, table, {col: codec} if codec else {}, () if codec else (col,), **how)
        return t.all().fetch(col).groupBy(F.expr(show).alias("v")).agg(F.count(F.lit(1)).alias("n"))

    return run


def trip(name: str, table: str, col: str, codec: Codec | None, show: str, sql: str, **how) -> None:
    add(f"encode_roundtrip_{name}", round_trip(table, col, codec, show, **how), f"SELECT {sql} AS v, count(*)::BIGINT AS n FROM {table} GROUP BY 1")


trip("int", "lineitem", "l_quantity", QUANTITY, "cast(l_quantity as bigint)", "l_quantity::BIGINT")
trip("signed", "customer", "c_acctbal", CENTS, "cast(c_acctbal * 100 as bigint)", "round(c_acctbal * 100)::BIGINT", bias="block")
trip("long", "orders", "o_orderkey", KEY, "o_orderkey % 97", "o_orderkey % 97", bias="block")
trip("date", "lineitem", "l_shipdate", DAYS, "cast(l_shipdate as string)", "l_shipdate::DATE::VARCHAR")
trip("ts", "events", "ts", TimestampCodec(), "date_format(ts, 'yyyy-MM-dd HH')", "strftime(ts, '%Y-%m-%d %H')", bias="block")
trip("decimal", "lineitem", "l_extendedprice", CENTS, "cast(l_extendedprice * 100 as bigint) % 1000", "round(l_extendedprice * 100)::BIGINT % 1000", bias="block")
trip("double", "customer", "c_acctbal", DoubleCodec(), "round(c_acctbal, 0)", "round(c_acctbal, 0)")
trip("double_positive", "events", "value", DoubleCodec(), "round(value, 0)", "round(value, 0)", bias="block")
trip("string", "part", "p_brand", None, "p_brand", "p_brand")
add("encode_roundtrip_bool", lambda spark, d: SlicedTable.from_df(load_addressed(spark, d, "labels").withColumn("flag", F.col("toxic") == 1), {"flag": BoolCodec()}).all().fetch("flag").groupBy("flag").agg(F.count(F.lit(1)).alias("n")), "SELECT toxic = 1 AS flag, count(*)::BIGINT AS n FROM labels GROUP BY 1")
add("encode_roundtrip_nulls", lambda spark, d: labelled(spark, d).all().fetch("doc_id", "quality", "toxic"), "SELECT doc_id, quality, toxic FROM documents LEFT JOIN labels USING (doc_id)")


def by_aggregates(spark: SparkSession, d: str) -> DataFrame:
    return sliced(spark, d, "lineitem", LINEITEM, bias="block", engine="catalyst").where(PREDICATES["and"]).count()


add("encode_catalyst", by_aggregates, f"SELECT count(*)::BIGINT AS n FROM lineitem WHERE {PREDICATES['and']}")


def via_blocks(spark: SparkSession, d: str) -> DataFrame:
    df = load_addressed(spark, d, "orders", ["o_orderkey", "o_totalprice"])
    codecs = {"o_orderkey": KEY, "o_totalprice": CENTS}
    m = encode.plan(df, codecs, "block")
    back = encode.from_blocks(encode.to_blocks(df, codecs, m), m)
    return back.agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("sum_key"), F.sum("o_totalprice").alias("sum_cents"))


add("encode_blocks", via_blocks, "SELECT count(*)::BIGINT AS n, sum(o_orderkey)::BIGINT AS sum_key, sum(round(o_totalprice * 100)::BIGINT)::BIGINT AS sum_cents FROM orders")


def block_widths(spark: SparkSession, d: str) -> DataFrame:
    t = sliced(spark, d, "orders", {"o_orderkey": KEY}, bias="block")
    return t.words.select("block_id", F.col("n").cast("long").alias("n"), F.col("o_orderkey__bits").cast("long").alias("bits"), F.col("o_orderkey__mn").alias("mn"), F.col("o_orderkey__mx").alias("mx")).distinct()


add("block_header_stats", block_widths, """SELECT block_id, count(*)::BIGINT AS n, length(format('{:b}', max(o_orderkey) - min(o_orderkey)))::BIGINT AS bits, min(o_orderkey) AS mn, max(o_orderkey) AS mx
FROM (SELECT o_orderkey, file_row_number // 1024 AS block_id FROM (SELECT o_orderkey, row_number() OVER () - 1 AS file_row_number FROM orders)) GROUP BY block_id""")
add("encoded_bytes", lambda spark, d: sliced(spark, d, "lineitem", {"l_quantity": QUANTITY}).memory_bytes().select("bytes", "rows"), "SELECT ((count(*) + 63) // 64 * 48)::BIGINT AS bytes, count(*)::BIGINT AS rows FROM lineitem")


# --- types

def typed(name: str, table: str, col: str, codec: Codec | None, text: str, key: str, sql: str | None = None, **how) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        t = sliced(spark, d, table, {col: codec, key: KEY} if codec else {key: KEY}, () if codec else (col,), **how)
        return t.where(text).fetch(key).agg(F.count(F.lit(1)).alias("n"), F.sum(key).alias("sum_key"))

    add(name, run, f"SELECT count(*)::BIGINT AS n, sum({key})::BIGINT AS sum_key FROM {table} WHERE {sql or text}")


typed("long_gt_shipdate", "lineitem", "l_shipdate", DAYS, "l_shipdate > DATE '1995-06-15'", "l_orderkey")
typed("long_eq_shipdate", "lineitem", "l_shipdate", DAYS, "l_shipdate = DATE '1995-06-15'", "l_orderkey")
typed("ts_between_events", "events", "ts", TimestampCodec(), "ts BETWEEN TIMESTAMP '2024-01-02 03:00:00' AND TIMESTAMP '2024-01-05 12:30:00'", "event_id", bias="block")
typed("double_gt_acctbal", "customer", "c_acctbal", DoubleCodec(), "c_acctbal > 0", "c_custkey")
typed("double_between_acctbal", "customer", "c_acctbal", DoubleCodec(), "c_acctbal BETWEEN 1000 AND 5000", "c_custkey")
typed("double_gt_value", "events", "value", DoubleCodec(), "value > 100", "event_id")
typed("double_between_value", "events", "value", DoubleCodec(), "value BETWEEN 10 AND 100", "event_id")
typed("decimal_between_price", "lineitem", "l_extendedprice", CENTS, "l_extendedprice BETWEEN 10000.25 AND 20000.75", "l_orderkey")
typed("str_eq_brand", "part", "p_brand", None, "p_brand = 'Brand#7'", "p_partkey")
typed("str_in_brand", "part", "p_brand", None, "p_brand IN ('Brand#7', 'Brand#11', 'Brand#20', 'Brand#2')", "p_partkey")
typed("str_eq_pname", "part", "p_name", None, "p_name = 'blue anvil'", "p_partkey")
typed("str_unknown", "part", "p_name", None, "p_name = 'no such part'", "p_partkey")
typed("str_prefix_pname", "part", "p_name", None, "p_name LIKE 'blue%'", "p_partkey")
typed("str_like_pname", "part", "p_name", None, "p_name LIKE '%an_il%'", "p_partkey")
typed("str_range_lang", "documents", "lang", None, "lang > 'de' AND lang <= 'fr'", "doc_id")
typed("str_not_in_type", "part", "p_type", None, "p_type NOT IN ('ECONOMY', 'STANDARD')", "p_partkey")


def day_seconds(spark: SparkSession, d: str, text: str = "secs > 43200") -> DataFrame:
    secs = (F.hour("ts") * 3600 + F.minute("ts") * 60 + F.floor(F.second("ts"))).cast("long")
    t = SlicedTable.from_df(load_addressed(spark, d, "events", ["ts", "event_id"]), {"secs": (KEY, secs), "event_id": KEY})
    return t.where(text).fetch("event_id").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("sum_key"))


add("ts_daysec_gt", day_seconds, "SELECT count(*)::BIGINT AS n, sum(event_id)::BIGINT AS sum_key FROM events WHERE hour(ts) * 3600 + minute(ts) * 60 + second(ts) > 43200")
add("ts_daysec_eq", lambda spark, d: day_seconds(spark, d, "secs BETWEEN 43200 AND 43260 OR secs = 86399"), "SELECT count(*)::BIGINT AS n, sum(event_id)::BIGINT AS sum_key FROM events WHERE hour(ts) * 3600 + minute(ts) * 60 + second(ts) BETWEEN 43200 AND 43260 OR hour(ts) * 3600 + minute(ts) * 60 + second(ts) = 86399")
typed("long_gt_orderdate", "orders", "o_orderdate", DAYS, "o_orderdate > DATE '1996-01-01'", "o_orderkey")
typed("long_us_shipdate", "lineitem", "l_shipdate", TimestampCodec(), "l_shipdate = TIMESTAMP '1995-06-15 00:00:00'", "l_orderkey")
add("bool_eq_toxic", lambda spark, d: SlicedTable.from_df(load_addressed(spark, d, "labels").withColumn("flag", F.col("toxic") == 1), {"flag": BoolCodec(), "doc_id": KEY}).where("flag = true").fetch("doc_id"), "SELECT doc_id FROM labels WHERE toxic = 1")


def compared(spark: SparkSession, d: str) -> DataFrame:
    df = load_addressed(spark, d, "lineitem", ["l_linenumber", "l_quantity"])
    return SlicedTable.from_df(df, {"l_linenumber": QUANTITY, "l_quantity": QUANTITY}, common_base=True).where("l_linenumber > l_quantity").count()


add("cols_gt", compared, "SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_linenumber > l_quantity")

# --- end-to-end patterns: counts and rows

PATTERNS = {
    "q1_quantity": ("lineitem", {"l_quantity": QUANTITY, "l_orderkey": KEY}, "l_quantity > 25", "l_orderkey"),
    "q2_offset": ("customer", {"c_acctbal": CENTS, "c_custkey": KEY}, "c_acctbal BETWEEN 9000 AND 9800", "c_custkey"),
    "q3_dates": ("lineitem", {"l_shipdate": DAYS, "l_orderkey": KEY}, "l_shipdate BETWEEN DATE '1995-01-01' AND DATE '1996-05-15'", "l_orderkey"),
    "q4_skewed": ("events", {"value": CENTS, "event_id": KEY}, "value > 200", "event_id"),
    "q5_compound": ("lineitem", LINEITEM, "l_quantity > 12 AND l_extendedprice BETWEEN 5000 AND 80000", "l_orderkey"),
}
for name, (tab, cods, text, key) in PATTERNS.items():
    add(f"{name}_count", lambda spark, d, tab=tab, cods=cods, text=text: sliced(spark, d, tab, cods).where(text).count(), f"SELECT count(*)::BIGINT AS n FROM {tab} WHERE {text}")
    add(f"{name}_rows", lambda spark, d, tab=tab, cods=cods, text=text, key=key: sliced(spark, d, tab, cods).where(text).fetch(key), f"SELECT {key} FROM {tab} WHERE {text}")


# --- consumers of masks

def line(spark: SparkSession, d: str, **how) -> SlicedTable:
    return sliced(spark, d, "lineitem", LINEITEM | {"l_shipdate": DAYS}, ("l_returnflag",), **how)


def summary(spark: SparkSession, d: str) -> DataFrame:
    return line(spark, d).where("l_quantity > 25").summary("l_extendedprice").select("n", F.col("sum_ord").cast("long").alias("sum_cents"), F.col("min_ord").alias("min_cents"), F.col("max_ord").alias("max_cents"))


add("sliced_sum_min_max", summary, "SELECT count(*)::BIGINT AS n, sum(c)::BIGINT AS sum_cents, min(c) AS min_cents, max(c) AS max_cents FROM (SELECT round(l_extendedprice * 100)::BIGINT AS c FROM lineitem WHERE l_quantity > 25)")
add("sliced_avg", lambda spark, d: line(spark, d).where("l_extendedprice < 50000").summary("l_quantity").select(F.round(F.col("sum_ord").cast("double") / F.col("n"), 6).alias("avg_q")), "SELECT round(sum(l_quantity) / count(*), 6) AS avg_q FROM lineitem WHERE l_extendedprice < 50000")


def variance(spark: SparkSession, d: str) -> DataFrame:
    t = line(spark, d)
    x = aggregate.second_moment(t.where("l_extendedprice < 50000").masked, t.manifest["l_quantity"])
    n, s, q = (F.col(c).cast("double") for c in ("n", "sum_above", "sum_squares_above"))
    return x.select(F.round(q / n - (s / n) * (s / n), 4).alias("var_q"))


add("sliced_variance", variance, "SELECT round(var_pop(l_quantity), 4) AS var_q FROM lineitem WHERE l_extendedprice < 50000")


def median(spark: SparkSession, d: str) -> DataFrame:
    t = line(spark, d)
    sel = t.where("l_quantity > 25")
    with t:  # several counting jobs read the same planes
        n = sel.count().first()[0]
        found = [sel.kth("l_extendedprice", k) for k in ((n - 1) // 2, n - 1)]
    return spark.createDataFrame([tuple(found)], "median_cents long, top_cents long")


add("sliced_median", median, "SELECT quantile_disc(round(l_extendedprice * 100)::BIGINT, 0.5) AS median_cents, max(round(l_extendedprice * 100)::BIGINT) AS top_cents FROM lineitem WHERE l_quantity > 25")
add("sliced_group_sum", lambda spark, d: line(spark, d).where("l_quantity > 25").group_sum("l_returnflag", "l_extendedprice").select("l_returnflag", "n", F.col("sum_ord").cast("long").alias("sum_cents")), "SELECT l_returnflag, count(*)::BIGINT AS n, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS sum_cents FROM lineitem WHERE l_quantity > 25 GROUP BY 1")
add("sliced_distinct", lambda spark, d: line(spark, d).where("l_quantity = 7 AND l_extendedprice < 9000").distinct("l_returnflag"), "SELECT DISTINCT l_returnflag FROM lineitem WHERE l_quantity = 7 AND l_extendedprice < 9000")
add("distinct_wide", lambda spark, d: line(spark, d).where("l_quantity = 50").distinct("l_extendedprice").select((F.col("l_extendedprice") * 100).cast("long").alias("cents")), "SELECT DISTINCT round(l_extendedprice * 100)::BIGINT AS cents FROM lineitem WHERE l_quantity = 50")
add("group_sum_wide", lambda spark, d: line(spark, d).where("l_quantity > 25").group_sum("l_orderkey", "l_extendedprice").select("l_orderkey", "n", F.col("sum_ord").cast("long").alias("sum_cents")), "SELECT l_orderkey, count(*)::BIGINT AS n, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS sum_cents FROM lineitem WHERE l_quantity > 25 GROUP BY 1")


def emptied(spark: SparkSession, d: str) -> DataFrame:
    none = load_addressed(spark, d, "lineitem", ["l_quantity", "l_extendedprice"]).where("l_quantity < 0")
    t = SlicedTable.from_df(none, {"l_quantity": QUANTITY, "l_extendedprice": CENTS}).all()
    assert t.distinct("l_quantity").isEmpty()
    return t.group_sum("l_quantity", "l_extendedprice").select("l_quantity", "n", F.col("sum_ord").cast("long").alias("sum_cents"))


add("group_sum_empty", emptied, "SELECT l_quantity::INTEGER AS l_quantity, count(*)::BIGINT AS n, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS sum_cents FROM lineitem WHERE l_quantity < 0 GROUP BY 1")
add("mask_sample", lambda spark, d: line(spark, d).where("l_quantity > 25").sample(0.5).fetch("l_orderkey").agg((F.abs(F.count(F.lit(1)) * 2 - load(spark, d, "lineitem").where("l_quantity > 25").count()) * 5 < F.count(F.lit(1))).alias("near_half")), "SELECT true AS near_half")
add("sliced_topk", lambda spark, d: line(spark, d).where("l_quantity > 25").fetch("l_extendedprice", "l_orderkey").orderBy(F.desc("l_extendedprice"), "l_orderkey").limit(10).select((F.col("l_extendedprice") * 100).cast("long").alias("cents"), "l_orderkey"), "SELECT round(l_extendedprice * 100)::BIGINT AS cents, l_orderkey FROM lineitem WHERE l_quantity > 25 ORDER BY 1 DESC, 2 LIMIT 10")


def materialised(spark: SparkSession, d: str) -> DataFrame:
    base = load_addressed(spark, d, "lineitem")
    t = SlicedTable.from_df(base, {"l_quantity": QUANTITY})
    return t.where("l_quantity = 50").late("l_orderkey", "l_linenumber", "l_shipdate")


add("late_materialise", materialised, "SELECT l_orderkey, l_linenumber, l_shipdate FROM lineitem WHERE l_quantity = 50")


def residual(spark: SparkSession, d: str) -> DataFrame:
    base = load_addressed(spark, d, "part")
    t = SlicedTable.from_df(base, {"p_size": QUANTITY})
    mine, rest = planner.split(parse("p_size > 25 AND p_name LIKE '%anvil'"), t.manifest)
    return t.filter_with_residual(mine, "p_name LIKE '%anvil'" if rest else None, ["p_partkey", "p_size"])


add("residual_like", residual, "SELECT p_partkey, p_size FROM part WHERE p_size > 25 AND p_name LIKE '%anvil'")


def masks(spark: SparkSession, d: str) -> DataFrame:
    w = line(spark, d).mask_each(["l_quantity > 25", "l_extendedprice < 50000"])
    pop = lambda m: F.sum(F.bit_count(m)).cast("long")
    a, b = F.col("mask0"), F.col("mask1")
    return w.agg(pop(a.bitwiseAND(b)).alias("both"), pop(a.bitwiseOR(b)).alias("either"), pop(a.bitwiseAND(F.bitwise_not(b))).alias("first_only"))


add("mask_set_ops", masks, "SELECT count(*) FILTER (a AND b)::BIGINT AS both, count(*) FILTER (a OR b)::BIGINT AS either, count(*) FILTER (a AND NOT b)::BIGINT AS first_only FROM (SELECT l_quantity > 25 AS a, l_extendedprice < 50000 AS b FROM lineitem)")

# --- skipping and planning

add("zone_skip_orderkey", lambda spark, d: sliced(spark, d, "orders", {"o_orderkey": KEY}, bias="block").where("o_orderkey BETWEEN 2000 AND 2999").fetch("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderkey BETWEEN 2000 AND 2999")


def skipping_counts(spark: SparkSession, d: str) -> DataFrame:
    t = sliced(spark, d, "orders", {"o_orderkey": KEY}, bias="block")
    return skipping.skipped(t.words, t.manifest, binding.bind(parse("o_orderkey > 14000"), t.manifest))


add("zone_skip_words", skipping_counts, """WITH b AS (SELECT o_orderkey, (row_number() OVER () - 1) // 1024 AS b, (row_number() OVER () - 1) // 64 AS w FROM orders),
k AS (SELECT b, max(o_orderkey) > 14000 AS keep FROM b GROUP BY b) SELECT count(DISTINCT w)::BIGINT AS words, (count(DISTINCT w) FILTER (keep))::BIGINT AS kept FROM b JOIN k USING (b)""")


def bloom(spark: SparkSession, d: str) -> DataFrame:
    t = sliced(spark, d, "lineitem", {"l_orderkey": KEY, "l_quantity": QUANTITY}, bias="block", bloom=("l_orderkey",))
    return t.where("l_orderkey IN (77, 4242, 999999999)").fetch("l_orderkey", "l_quantity")


add("bloom_in", bloom, "SELECT l_orderkey, l_quantity::INTEGER AS l_quantity FROM lineitem WHERE l_orderkey IN (77, 4242, 999999999)")


def representations(spark: SparkSession, d: str) -> DataFrame:
    micros = TimestampCodec().ordinal(F.col("l_shipdate"))
    cols = {"line": F.col("l_linenumber"), "order": F.col("l_orderkey"), "micros": micros, "spread": F.col("l_orderkey") * 5_000_000_000 + F.col("l_partkey")}
    return planner.representation_table(load(spark, d, "lineitem"), cols).select("column", "planes", "choice")


def represented(name: str, sql: str) -> str:
    return f"SELECT '{name}' AS name, max({sql})::BIGINT - min({sql})::BIGINT AS range, count(DISTINCT {sql}) AS k FROM lineitem"


add("choose_representation", representations, f"""SELECT name AS "column", greatest(1, length(format('{{:b}}', range)))::INTEGER AS planes,
CASE WHEN length(format('{{:b}}', range)) <= 16 THEN 'sliced' WHEN k <= {planner.DICTIONARY} THEN 'dict' WHEN length(format('{{:b}}', range)) < 32 THEN 'sliced' ELSE 'plain' END AS choice
FROM ({" UNION ALL ".join(represented(n, q) for n, q in (("line", "l_linenumber"), ("order", "l_orderkey"), ("micros", "epoch_us(l_shipdate)"), ("spread", "(l_orderkey * 5000000000 + l_partkey)")))})""")


def cost(spark: SparkSession, d: str) -> DataFrame:
    e = sliced(spark, d, "lineitem", {"l_quantity": QUANTITY}).explain("l_quantity BETWEEN 10 AND 19")
    return spark.createDataFrame([(e["passes"], e["ops"], e["bytes"])], "passes long, ops long, bytes long")


add("cost_estimate", cost, "SELECT 12::BIGINT AS passes, (13 * ((count(*) + 63) // 64))::BIGINT AS ops, (12 * count(*) // 8)::BIGINT AS bytes FROM lineitem")

# --- baselines

Q1_SQL = "SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_quantity > 25"
add("base_scalar", lambda spark, d: baselines.scalar(load(spark, d, "lineitem"), "l_quantity > 25"), Q1_SQL)
add("base_boxed", lambda spark, d: baselines.boxed(load(spark, d, "lineitem"), "l_quantity", lambda x: x > 25), Q1_SQL)
add("base_arrow", lambda spark, d: baselines.arrow(load(spark, d, "lineitem"), "l_quantity", "gt", 25), Q1_SQL)
add("base_arrow_accessor", lambda spark, d: baselines.arrow(load(spark, d, "lineitem"), "l_quantity", "gt", 25, False), Q1_SQL)
add("base_parquet_materialised", lambda spark, d: baselines.parquet_materialised(load(spark, d, "lineitem"), "l_quantity > 25"), Q1_SQL)
for name, tab, text in (("long", "events", "ts > TIMESTAMP_NTZ '2024-01-10 00:00:00'"), ("long_eq", "lineitem", "l_shipdate = TIMESTAMP_NTZ '1995-06-15 00:00:00'"), ("double", "customer", "c_acctbal BETWEEN 1000 AND 5000"), ("string", "part", "p_brand = 'Brand#7'"), ("string_in", "part", "p_brand IN ('Brand#7', 'Brand#11', 'Brand#20', 'Brand#2')")):
    add(f"base_scalar_{name}", lambda spark, d, tab=tab, text=text: baselines.scalar(load(spark, d, tab), text), f"SELECT count(*)::BIGINT AS n FROM {tab} WHERE {text.replace('_NTZ', '')}")
add("base_parquet_pushdown", lambda spark, d: baselines.parquet_pushdown(load(spark, d, "orders"), "o_orderkey > 14000"), "SELECT count(*)::BIGINT AS n FROM orders WHERE o_orderkey > 14000")


def dict_codes(spark: SparkSession, d: str) -> DataFrame:
    df = load_addressed(spark, d, "part", ["p_brand"])
    known = dictionary.build(df, "p_brand")
    return baselines.dict_scan(df.select(known.ordinal(F.col("p_brand")).alias("code")), "code", ["Brand#7", "Brand#11"], list(known.values))


add("base_dict_scan", dict_codes, "SELECT count(*)::BIGINT AS n FROM part WHERE p_brand IN ('Brand#7', 'Brand#11')")
add("dict_table", lambda spark, d: dictionary.table(load(spark, d, "customer"), "c_name"), "SELECT value, row_number() OVER (ORDER BY value) - 1 AS code FROM (SELECT DISTINCT c_name AS value FROM customer)")
add("base_hash_in", lambda spark, d: baselines.hash_in(load(spark, d, "lineitem"), "l_orderkey", load(spark, d, "orders").where("o_totalprice > 400000").select(F.col("o_orderkey").alias("l_orderkey"))), "SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_totalprice > 400000)")
add("base_point_lookup", lambda spark, d: baselines.point_lookup(load(spark, d, "orders", ["o_orderkey", "o_custkey"]), "o_orderkey", [5, 77]), "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey IN (5, 77)")

# --- measures as small tables

#: Rows of lineitem and the largest value of three columns; planes and sizes follow from them.
SIZES = ["count(*) AS n", "max(cast(l_quantity AS bigint)) AS l_quantity", "max(l_orderkey) AS l_orderkey", "max(cast(round(l_extendedprice * 100) AS bigint)) AS l_extendedprice"]
SIZED = ("l_quantity", "l_orderkey", "l_extendedprice")
SIZES_SQL = """WITH s AS (SELECT count(*)::BIGINT AS n, max(l_quantity::BIGINT) AS q, max(l_orderkey) AS o, max(round(l_extendedprice * 100)::BIGINT) AS c FROM lineitem),
w AS (SELECT n, unnest(['l_quantity', 'l_orderkey', 'l_extendedprice']) AS col, unnest([1, 2, 3]) AS k, unnest([q, o, c]) AS top FROM s),
b AS (SELECT n, col, k, length(format('{:b}', coalesce(top, 0)))::BIGINT AS b FROM w) """


def measure(rows: Callable[[int, dict[str, int]], list[tuple]], schema: str) -> Query:
    """A measure over lineitem: ``rows`` gets the number of rows and the planes of each column."""
    kind = "array<struct<" + ", ".join(f.replace(" ", ": ") for f in schema.split(", ")) + ">>"

    def run(spark: SparkSession, d: str) -> DataFrame:
        each = F.udf(lambda s: rows(s["n"], {c: metrics.width(s[c] or 0) for c in SIZED}), kind)
        return load(spark, d, "lineitem").selectExpr(*SIZES).select(F.explode(each(F.struct("*"))).alias("x")).select("x.*")

    return run


add("m_compression", measure(lambda n, b: [(c, b[c], metrics.compression_ratio(b[c])) for c in SIZED], "col string, b long, ratio double"), SIZES_SQL + "SELECT col, b, 32.0::DOUBLE / b AS ratio FROM b")
add("m_block_bytes", measure(lambda n, b: [(c, k, metrics.block_bytes(k, b[c], 64)) for c in SIZED for k in (64, 1000, 1024, n)], "col string, n long, bytes long"), SIZES_SQL + "SELECT col, t.n::BIGINT AS n, (b * ((t.n + 63) // 64) * 8)::BIGINT AS bytes FROM b, (SELECT unnest([64, 1000, 1024, s.n]) AS n FROM s) t")
add("m_passes", measure(lambda n, b: [(c, k, metrics.plane_passes(k.split("_")[0], b[c], int((k.split("_") + ["1"])[1]))) for c in SIZED for k in ("eq", "gt", "between", "in_4", "in_16")], "col string, kind string, passes long"), SIZES_SQL + "SELECT col, kind, (b * times)::BIGINT AS passes FROM b, (VALUES ('eq', 1), ('gt', 1), ('between', 2), ('in_4', 4), ('in_16', 16)) t(kind, times)")
#: In register operations: encoding sets a bit for each value and plane, a scalar scan compares each value, a sliced one reads the planes' words.
add("m_break_even", measure(lambda n, b: [(c, round(metrics.break_even(n * b[c], float(n), metrics.plane_ops(n, b[c])), 1)) for c in SIZED], "col string, scans double"), SIZES_SQL + "SELECT col, CASE WHEN n > b * n / 64.0::DOUBLE THEN round(n * b / (n - b * n / 64.0::DOUBLE), 1) ELSE 'inf'::DOUBLE END AS scans FROM b")
add("m_compound_cost", measure(lambda n, b: [(k, metrics.compound_ops([b[c] for c in SIZED[:k]], n)) for k in (1, 2, 3)], "k long, ops double"), SIZES_SQL + "SELECT k::BIGINT AS k, ((sum(b) OVER (ORDER BY k) + k - 1) * n)::BIGINT / 64.0::DOUBLE AS ops FROM b")
#: The quantities of 100,000 such tables in nodes of 1,000 GB: boxed, as 32-bit integers and in planes.
add("m_economics", measure(lambda n, b: [(k, *metrics.economics(n * 1e5, v, 1000, u).values()) for k, v, u in (("boxed", 24.0, 6.0), ("int", 4.0, 2.0), ("sliced", metrics.bytes_per_value(b["l_quantity"]), 0.5))], "kind string, gb double, nodes long, usd_hour double, usd_year double"), SIZES_SQL + """, v AS (SELECT t.kind, n * 100000.0::DOUBLE * CASE t.kind WHEN 'sliced' THEN b / 8.0::DOUBLE ELSE t.v END / 1000000000.0::DOUBLE AS gb, t.u FROM b, (VALUES ('boxed', 24.0::DOUBLE, 6.0::DOUBLE), ('int', 4.0, 2.0), ('sliced', NULL, 0.5)) t(kind, v, u) WHERE k = 1)
SELECT kind, gb, greatest(1, ceil(gb / 1000))::BIGINT AS nodes, greatest(1, ceil(gb / 1000)) * u AS usd_hour, greatest(1, ceil(gb / 1000)) * u * 2000 AS usd_year FROM v""")
#: A partition of 1,000 rows takes its plane operations, at a thousand a millisecond.
add("m_cluster_seconds", measure(lambda n, b: [(c, -(-n // 1000), metrics.cluster_seconds(-(-n // 1000), metrics.plane_ops(1000, b[c]) / 1000)) for c in SIZED], "col string, partitions long, seconds double"), SIZES_SQL + "SELECT col, ((n + 999) // 1000)::BIGINT AS partitions, ((n + 999) // 1000) * (b * 1000 / 64.0::DOUBLE / 1000.0::DOUBLE) / 1000.0::DOUBLE AS seconds FROM b")

# --- sweeps

def selectivity(spark: SparkSession, d: str) -> DataFrame:
    cuts = [104875.15, 103940.14, 94709.31, 53028.16, 11352.49]
    w = sliced(spark, d, "lineitem", {"l_extendedprice": CENTS}).mask_each([f"l_extendedprice > {c}" for c in cuts])
    got = w.agg(*[F.sum(F.bit_count(f"mask{i}")).cast("long").alias(f"n{i}") for i in range(len(cuts))])
    return got.select(F.explode(F.array(*[F.struct(F.lit(c).alias("cut"), F.col(f"n{i}").alias("n")) for i, c in enumerate(cuts)])).alias("x")).select("x.*")


add("sel_sweep", selectivity, "SELECT cut, count(*)::BIGINT AS n FROM (VALUES (104875.15::DOUBLE), (103940.14), (94709.31), (53028.16), (11352.49)) t(cut) JOIN lineitem ON l_extendedprice > cut GROUP BY cut")


def widths(spark: SparkSession, d: str) -> DataFrame:
    """Columns of 1 to 32 planes, each compared with the middle of its range."""
    df = load_addressed(spark, d, "lineitem", ["l_orderkey", "l_partkey"])
    spread = F.col("l_orderkey") * 2654435761 + F.col("l_partkey") * 40503
    bits = range(1, 33)
    t = SlicedTable.from_df(df, {f"w{b}": (KEY, spread.bitwiseAND(F.lit((1 << b) - 1))) for b in bits}, bias="none", widths={f"w{b}": b for b in bits})
    w = t.mask_each([f"w{b} > {(1 << b) // 2 - 1}" for b in bits])
    got = w.agg(*[F.sum(F.bit_count(f"mask{b - 1}")).cast("long").alias(f"n{b}") for b in bits])
    return got.select(F.explode(F.array(*[F.struct(F.lit(t.manifest[f"w{b}"].planes).alias("planes"), F.col(f"n{b}").alias("n")) for b in bits])).alias("x")).select("x.*")


add("width_sweep", widths, "SELECT b::INTEGER AS planes, (count(*) FILTER (((l_orderkey * 2654435761 + l_partkey * 40503) & ((1::BIGINT << b) - 1)) > (1::BIGINT << b) // 2 - 1))::BIGINT AS n FROM lineitem, range(1, 33) t(b) GROUP BY b")


def block_sizes(spark: SparkSession, d: str) -> DataFrame:
    df = load_addressed(spark, d, "orders", ["o_orderkey"])
    out = None
    for size in (256, 1024, 4096, 16384):
        t = SlicedTable.from_df(df, {"o_orderkey": KEY}, bias="block", block_size=size)
        one = t.words.select("block_id", "o_orderkey__bits").distinct().agg(F.lit(size).alias("size"), F.count(F.lit(1)).alias("blocks"), F.max("o_orderkey__bits").cast("int").alias("bits"))
        out = one if out is None else out.unionByName(one)
    return out


add("block_size_sweep", block_sizes, "SELECT s AS size, count(DISTINCT r // s)::BIGINT AS blocks, least(length(format('{:b}', (s - 1)::BIGINT)), length(format('{:b}', max(r))))::INTEGER AS bits FROM (SELECT row_number() OVER () - 1 AS r FROM orders), (VALUES (256), (1024), (4096), (16384)) t(s) GROUP BY s")


#: The three columns of the throughput and footprint experiments: table, expression, predicate at about half of the rows, and SQL of both.
DATASETS = {
    "d1": ("lineitem", "cast(l_quantity as bigint)", 25, "l_quantity::BIGINT"),
    "d2": ("lineitem", "floor(l_extendedprice)", 52923, "floor(l_extendedprice)::BIGINT"),
    "d3": ("orders", "o_orderkey * 400", 400 * 700, "o_orderkey * 400"),
}


def dataset(spark: SparkSession, d: str, name: str, **how) -> SlicedTable:
    tab, value, _, _ = DATASETS[name]
    return SlicedTable.from_df(load_addressed(spark, d, tab), {"x": (KEY, F.expr(value))}, bias="none", **how)


for name, (tab, _, cut, sql) in DATASETS.items():
    add(f"throughput_{name}", lambda spark, d, name=name, cut=cut: dataset(spark, d, name).where(f"x > {cut}").count(), f"SELECT count(*)::BIGINT AS n FROM {tab} WHERE {sql} > {cut}")


def footprints(spark: SparkSession, d: str) -> DataFrame:
    """Bytes a value of each representation: planes, 32-bit integers, boxed objects of 24 bytes."""
    parts = None
    for name in DATASETS:
        t = dataset(spark, d, name)
        one = t.words.agg(F.lit(name).alias("name"), (F.count(F.lit(1)) * 8 * t.manifest["x"].planes).alias("sliced"), (F.sum(F.bit_count("live").cast("long")) * 4).alias("ints"), (F.sum(F.bit_count("live").cast("long")) * 24).alias("boxed"))
        parts = one if parts is None else parts.unionByName(one)
    return parts


add("footprint", footprints, " UNION ALL ".join(f"SELECT '{n}' AS name, ((count(*) + 63) // 64 * 8 * length(format('{{:b}}', max({sql}))))::BIGINT AS sliced, count(*)::BIGINT * 4 AS ints, count(*)::BIGINT * 24 AS boxed FROM {tab}" for n, (tab, _, _, sql) in DATASETS.items()))


def replicated(df: DataFrame, times: int) -> DataFrame:
    """An addressed table ``times`` over: every copy of a file is a file of its own."""
    return df.withColumn("__copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).withColumn(FILE, F.xxhash64(FILE, "__copy")).drop("__copy").repartition(times, FILE).sortWithinPartitions(FILE, ROW) if times > 1 else df


def scaled(spark: SparkSession, d: str) -> DataFrame:
    """The first pattern at one, two and four times the rows."""
    out = None
    for times in (1, 2, 4):
        df = replicated(load_addressed(spark, d, "lineitem", ["l_quantity"]), times)
        one = SlicedTable.from_df(df, {"l_quantity": QUANTITY}).where("l_quantity > 25").count().select(F.lit(times).alias("times"), "n")
        out = one if out is None else out.unionByName(one)
    return out


add("scaling", scaled, "SELECT k::INTEGER AS times, count(*) * k AS n FROM lineitem, (VALUES (1), (2), (4)) t(k) WHERE l_quantity > 25 GROUP BY k")


def coded_by_table(spark: SparkSession, df: DataFrame, col: str) -> tuple[int, SlicedTable, DataFrame, DataFrame]:
    """As the literal dictionary's part of ``cardinalities``, for any number of strings: codes come from a dictionary table."""
    path = scratch(spark, "dictionary")
    dictionary.table(df, col).write.parquet(path)
    known = spark.read.parquet(path)
    k, last = known.agg(F.count(F.lit(1)), F.max_by("code", "value")).first()
    coded = dictionary.codes(df, col, known).repartitionByRange(FILE, ROW).sortWithinPartitions(FILE, ROW)
    t = SlicedTable.from_df(coded, {"code": KEY}, bias="none")
    return k, t, t.where(f"code = {last}").count(), baselines.scalar(coded, f"code = {last}")


def cardinalities(spark: SparkSession, d: str) -> DataFrame:
    """Equality with the last of a column's strings: on planes of codes, and on codes that are not sliced."""
    out = None
    for tab, col in (("part", "p_type"), ("part", "p_brand"), ("part", "p_name"), ("customer", "c_name")):
        df = load_addressed(spark, d, tab, [col])
        try:
            known = dictionary.build(df, col)
        except dictionary.DictionaryTooLarge:
            k, t, planes, codes = coded_by_table(spark, df, col)
        else:
            k, last = len(known.values), known.values[-1]
            t = SlicedTable.from_df(df, {col: known})
            planes = t.where(f"{col} = '{last}'").count()
            codes = baselines.dict_scan(df.select(known.ordinal(F.col(col)).alias("code")), "code", [last], list(known.values))
        planes, codes = planes.select(F.col("n").alias("on_planes")), codes.select(F.col("n").alias("on_codes"))
        one = planes.join(codes).select(F.lit(col).alias("col"), F.lit(k).alias("k"), F.lit(t.manifest.columns[0].planes).alias("planes"), "on_planes", "on_codes")  # one row each
        out = one if out is None else out.unionByName(one)
    return out


add("dictionary_cardinality", cardinalities, " UNION ALL ".join(f"SELECT '{c}' AS col, count(DISTINCT {c})::INTEGER AS k, greatest(1, length(format('{{:b}}', count(DISTINCT {c}) - 1)))::INTEGER AS planes, (count(*) FILTER ({c} = (SELECT max({c}) FROM {t})))::BIGINT AS on_planes, (count(*) FILTER ({c} = (SELECT max({c}) FROM {t})))::BIGINT AS on_codes FROM {t}" for t, c in (("part", "p_type"), ("part", "p_brand"), ("part", "p_name"), ("customer", "c_name"))))


def mixed(spark: SparkSession, d: str) -> DataFrame:
    """One block in ten is wide: adaptive width against one width for all."""
    base = load_addressed(spark, d, "lineitem", ["l_extendedprice", "l_quantity"])
    value = F.when(F.floor(F.col(ROW) / 1024) % 10 == 0, F.floor("l_extendedprice")).otherwise(F.col("l_quantity") % 16).cast("long")
    t = SlicedTable.from_df(base, {"x": (KEY, value)}, bias="none")
    return t.words.agg(F.sum(F.col("x__bits").cast("long")).alias("adaptive"), (F.count(F.lit(1)) * t.manifest["x"].planes).alias("fixed"))


add("mixed_blocks", mixed, """WITH r AS (SELECT l_extendedprice, l_quantity, row_number() OVER () - 1 AS i FROM lineitem),
x AS (SELECT i // 1024 AS b, i // 64 AS w, CASE WHEN (i // 1024) % 10 = 0 THEN floor(l_extendedprice)::BIGINT ELSE (l_quantity::BIGINT) % 16 END AS v FROM r),
b AS (SELECT b, length(format('{:b}', max(v))) AS bits, count(DISTINCT w) AS words FROM x GROUP BY b)
SELECT sum(bits * words)::BIGINT AS adaptive, (max(bits) * sum(words))::BIGINT AS fixed FROM b""")


def columns_sweep(spark: SparkSession, d: str) -> DataFrame:
    t = sliced(spark, d, "lineitem", {"l_quantity": QUANTITY, "l_extendedprice": CENTS, "l_linenumber": QUANTITY, "l_discount": CENTS, "l_tax": CENTS})
    parts = ["l_quantity > 5", "l_extendedprice < 95000", "l_linenumber <= 5", "l_discount >= 0.01", "l_tax < 0.08"]
    w = t.mask_each([" AND ".join(parts[: k + 1]) for k in range(len(parts))])
    got = w.agg(*[F.sum(F.bit_count(f"mask{i}")).cast("long").alias(f"n{i}") for i in range(len(parts))])
    return got.select(F.explode(F.array(*[F.struct(F.lit(k + 1).alias("k"), F.col(f"n{k}").alias("n")) for k in range(len(parts))])).alias("x")).select("x.*")


add("columns_sweep", columns_sweep, """SELECT k::INTEGER AS k, count(*)::BIGINT AS n FROM lineitem, range(1, 6) t(k) WHERE l_quantity > 5 AND (k < 2 OR l_extendedprice < 95000) AND (k < 3 OR l_linenumber <= 5)
AND (k < 4 OR round(l_discount * 100) >= 1) AND (k < 5 OR round(l_tax * 100) < 8) GROUP BY k""")

# --- surrounding operators and streams

for name, (query, sql) in (joins.WORKLOADS | relational.WORKLOADS).items():
    add(name, query, sql)


def ingest_count(spark: SparkSession, d: str) -> DataFrame:
    out, at = scratch(spark, "ingest"), scratch(spark, "ingest-checkpoint")
    streams.ingest(streams.stream(spark, f"{d}/events.parquet"), {"value": CENTS, "event_id": KEY}, out, at)
    return streams.ingested(spark, out).where("value > 200").fetch("event_id")


BEYOND = "CASE WHEN event_id % 7 = 0 THEN NULL WHEN event_id % 2 = 0 THEN event_id % 100 ELSE event_id % 1000 - 300 END"


def in_files(spark: SparkSession, rows: DataFrame, *conditions: str) -> str:
    """One file for the rows of each condition, in this order for a stream."""
    out = scratch(spark, "files")
    for k, condition in enumerate(conditions):
        time.sleep(k and 1)  # the file source orders files by time
        rows.where(condition).coalesce(1).write.mode("append").parquet(out)
    return out


def ingest_beyond(spark: SparkSession, d: str) -> DataFrame:
    """The second batch holds smaller and larger values than the first, and nulls."""
    rows = load(spark, d, "events").selectExpr("event_id", f"IF(event_id % 14 = 0, 50, {BEYOND}) AS x")
    files = in_files(spark, rows, "event_id % 2 = 0", "event_id % 2 = 1")
    out, at = scratch(spark, "ingest"), scratch(spark, "ingest-checkpoint")
    streams.ingest(streams.stream(spark, files), {"x": KEY, "event_id": KEY}, out, at)
    return bounded(streams.ingested(spark, out))


BOUNDS = {"above": "x > 110", "upto": "x <= 110", "below": "x < 0", "nulls": "x IS NULL", "known": "x >= -1000", "not_in": "x NOT IN (50, -300)"}


def bounded(t: SlicedTable) -> DataFrame:
    """Rows and sums of keys on either side of the first part's bounds."""
    out = None
    for name, text in BOUNDS.items():
        one = t.where(text).fetch("event_id").agg(F.lit(name).alias("name"), F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("sum_id"))
        out = one if out is None else out.unionByName(one)
    return out


def bounds_sql(value: str) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS name, count(*)::BIGINT AS n, sum(event_id)::BIGINT AS sum_id FROM (SELECT event_id, {value} AS x FROM events) WHERE {text}" for n, text in BOUNDS.items())


def appended(parts: tuple[str, str], **how) -> Query:
    """Two parts of an encoded dataset, the second appended beyond the first one's bounds."""
    def run(spark: SparkSession, d: str) -> DataFrame:
        path, codecs = scratch(spark, "appended"), {"x": KEY, "event_id": KEY}
        events = load_addressed(spark, d, "events", ["event_id"])
        first, second = (events.where(f"event_id % 2 = {k}").withColumn("x", F.expr(x)) for k, x in enumerate(parts))
        a = SlicedTable.from_df(first, codecs, **how)
        store.write_sliced(a, path)
        store.write_sliced(SlicedTable.from_df(second, codecs, like=a.manifest), path, mode="append")
        return bounded(store.read_sliced(spark, path))

    return run


add("append_bounds", appended(("event_id % 100", "event_id % 121 - 5"), bias="block"), bounds_sql("CASE WHEN event_id % 2 = 0 THEN event_id % 100 ELSE event_id % 121 - 5 END"))
add("append_nulls", appended(("event_id % 100", "IF(event_id % 5 = 0, NULL, event_id % 121)"), bias="none"), bounds_sql("CASE WHEN event_id % 2 = 0 THEN event_id % 100 WHEN event_id % 5 = 0 THEN NULL ELSE event_id % 121 END"))
add("stream_ingest_beyond", ingest_beyond, bounds_sql(f"CASE WHEN event_id % 14 = 0 THEN 50 ELSE {BEYOND} END"))


LATE = "ts < TIMESTAMP_NTZ '2024-01-06 00:00:00' AND event_id % 20 = 0"


def late_rows(spark: SparkSession, d: str) -> DataFrame:
    """A twentieth of the first days' rows comes with the end of the month, two batches after its windows could be closed."""
    day = "ts < TIMESTAMP_NTZ '2024-01-{} 00:00:00'".format
    files = in_files(spark, load(spark, d, "events"), f"{day(16)} AND NOT ({LATE})", f"NOT ({day(16)}) AND {day(20)}", f"NOT ({day(20)}) OR {LATE}")
    return streams.run_to_table(streams.late(streams.stream(spark, files), "1 hour", "1 day"), "late").selectExpr("date_format(start, 'yyyy-MM-dd') AS day", "n")


add("stream_late", late_rows, """SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, count(*)::BIGINT AS n FROM events WHERE NOT (ts < TIMESTAMP '2024-01-06' AND event_id % 20 = 0)
GROUP BY time_bucket(INTERVAL 1 DAY, ts) HAVING time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""")


def stream_blocks(spark: SparkSession, d: str) -> DataFrame:
    shards = streams.stream(spark, f"{d}/events.parquet").selectExpr("user_id % 4 AS shard", "event_id")
    blocks = streams.finished(streams.run_to_table(streams.block_builder(shards, "shard", "event_id", 256), "blocks"))
    return streams.unpacked(blocks).groupBy("shard").agg(F.count_distinct("block").alias("blocks"), F.count(F.lit(1)).alias("n"), F.sum("value").alias("sum_id"))


add("stream_blocks", stream_blocks, "SELECT user_id % 4 AS shard, (count(*) + 255) // 256 AS blocks, count(*)::BIGINT AS n, sum(event_id)::BIGINT AS sum_id FROM events GROUP BY 1")


def streamed(build: Callable[[DataFrame], DataFrame], label: str) -> Query:
    return lambda spark, d: streams.run_to_table(build(streams.timed(streams.stream(spark, f"{d}/events.parquet"), "30 days")), label, "complete")


START = "strftime({}, '%Y-%m-%d %H:%M:%S')"
SHOWN = "date_format(start, 'yyyy-MM-dd HH:mm:ss') AS start"
add("stream_ingest_count", ingest_count, "SELECT event_id FROM events WHERE value > 200")
add("stream_tumbling", lambda spark, d: streamed(streams.tumbling, "tumbling")(spark, d).selectExpr(SHOWN, "n", "cents"), f"SELECT {START.format('time_bucket(INTERVAL 1 DAY, ts)')} AS start, count(*)::BIGINT AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events GROUP BY 1")
add("stream_sliding", lambda spark, d: streamed(streams.sliding, "sliding")(spark, d).selectExpr(SHOWN, "n"), f"SELECT {START.format('time_bucket(INTERVAL 1 DAY, ts) - k * INTERVAL 1 DAY')} AS start, count(*)::BIGINT AS n FROM events, range(0, 2) t(k) GROUP BY 1")
add("stream_session", lambda spark, d: streamed(streams.sessions, "sessions")(spark, d).selectExpr("user_id", SHOWN, "n"), f"""WITH e AS (SELECT user_id, ts, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 12 HOUR, true)::INTEGER AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, {START.format('min(ts)')} AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k""")
