"""Joins around encoded filters."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codecs import DecimalCodec, IntCodec
from ..plans.predicates import in_list
from ..sources.tables import load, load_addressed
from . import dictionary
from .table import SlicedTable


def semi_by_slices(table: SlicedTable, col: str, keys: DataFrame, fetch: list[str], most: int = 1000) -> DataFrame:
    """A small key set becomes an IN list (on planes, or a hash set of ordinals); a larger one a semi join of the fetched rows."""
    key = keys.columns[0]
    few = keys.select(key).where(F.col(key).isNotNull()).distinct().limit(most + 1).collect()
    if len(few) <= most:
        return table.where(in_list(col, [r[0] for r in few])).fetch(*fetch)
    rows = table.all().fetch(*dict.fromkeys([*fetch, col]))
    return rows.join(keys.select(F.col(key).alias(col)).distinct(), col, "left_semi").select(*fetch)


def range_join(left: DataFrame, right: DataFrame, on: list[str], at: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with lo <= at <= hi: bucketed, so that it runs as an equi-join; ``width`` is about the ranges' length."""
    b = right.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return left.withColumn("__b", F.floor(F.col(at) / width)).join(b, [*on, "__b"]).where(F.col(at).between(F.col(lo), F.col(hi))).drop("__b")


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """The last right value at or before each left row, by one sorted pass over both sides."""
    a = left.select("*", F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v"))
    b = right.select(by, at, F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")


def _filtered(spark, d) -> DataFrame:
    codecs = {"l_quantity": IntCodec(), "l_orderkey": IntCodec(sql="bigint"), "l_extendedprice": DecimalCodec(scale=2)}
    t = SlicedTable.from_df(load_addressed(spark, d, "lineitem", list(codecs)), codecs)
    return t.where("l_quantity > 45").fetch("l_orderkey", "l_extendedprice")


def _star(spark, d) -> DataFrame:
    orders, customer, nation = (load(spark, d, t) for t in ("orders", "customer", "nation"))
    x = _filtered(spark, d).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    x = x.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows at any scale
    return x.groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("l_extendedprice") * 100).cast("long")).alias("cents"))


def _semi(spark, d) -> DataFrame:
    codecs = {"l_orderkey": IntCodec(sql="bigint"), "l_quantity": IntCodec()}
    t = SlicedTable.from_df(load_addressed(spark, d, "lineitem", list(codecs)), codecs)
    keys = load(spark, d, "orders").where("o_totalprice > 495000").select("o_orderkey")
    return semi_by_slices(t, "l_orderkey", keys, ["l_orderkey", "l_quantity"])


def _address(spark, d) -> DataFrame:
    df = load_addressed(spark, d, "lineitem", ["l_quantity", "l_linenumber"])
    a = SlicedTable.from_df(df, {"l_quantity": IntCodec()}).where("l_quantity > 25").masked.select("file_id", "block_id", "word_no", F.col("mask").alias("m1"))
    b = SlicedTable.from_df(df, {"l_linenumber": IntCodec()}).where("l_linenumber < 4").masked.select("file_id", "block_id", "word_no", F.col("mask").alias("m2"))
    return a.join(b, ["file_id", "block_id", "word_no"]).agg(F.sum(F.bit_count(F.col("m1").bitwiseAND(F.col("m2")))).cast("long").alias("n"))


def _range(spark, d) -> DataFrame:
    day = lambda c: F.unix_date(F.col(c).cast("date")).cast("long")
    lines = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), day("l_shipdate").alias("ship"))
    orders = load(spark, d, "orders").select(F.col("o_orderkey").alias("k"), day("o_orderdate").alias("lo"), (day("o_orderdate") + 30).alias("hi"))
    return range_join(lines, orders, ["k"], "ship", "lo", "hi", 64).agg(F.count(F.lit(1)).alias("n"))


def _as_of(spark, d) -> DataFrame:
    e = load(spark, d, "events")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(2).collect()]
    left = e.where(F.col("event_type") == kinds[0]).select("user_id", "ts", "event_id")
    right = e.where(F.col("event_type") == kinds[1]).groupBy("user_id", "ts").agg(F.max("event_id").alias("before_id"))
    return as_of(left, right, "user_id", "ts", "before_id").select("event_id", "before_id")


def _keys(spark, d, table: str, where: str, *cols: str) -> DataFrame:
    """Key columns of the rows of an encoded filter."""
    return SlicedTable.from_df(load_addressed(spark, d, table, list(cols)), {c: IntCodec(sql="bigint") for c in cols}).where(where).fetch(*cols)


WORKLOADS = {
    "join_star": (_star, "SELECT n_name, count(*)::BIGINT AS n, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE l_quantity > 45 GROUP BY n_name"),
    "join_semi_by_slices": (_semi, "SELECT l_orderkey, l_quantity::INTEGER AS l_quantity FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_totalprice > 495000)"),
    "join_left": (lambda spark, d: _keys(spark, d, "documents", "doc_id > 50", "doc_id").join(load(spark, d, "labels"), "doc_id", "left").groupBy("quality").agg(F.count(F.lit(1)).alias("n")), "SELECT quality, count(*)::BIGINT AS n FROM documents LEFT JOIN labels USING (doc_id) WHERE doc_id > 50 GROUP BY quality"),
    "join_anti": (lambda spark, d: _keys(spark, d, "documents", "doc_id > 50", "doc_id").join(load(spark, d, "labels"), "doc_id", "left_anti"), "SELECT doc_id FROM documents WHERE doc_id > 50 AND doc_id NOT IN (SELECT doc_id FROM labels)"),
    "join_full": (lambda spark, d: _keys(spark, d, "customer", "c_custkey < 100", "c_custkey").select(F.col("c_custkey").alias("k")).join(_keys(spark, d, "orders", "o_orderkey < 1000", "o_custkey", "o_orderkey").select(F.col("o_custkey").alias("k"), "o_orderkey"), "k", "full").agg(F.count("k").alias("n"), F.count("o_orderkey").alias("orders")), "SELECT count(coalesce(c_custkey, o_custkey))::BIGINT AS n, count(o_orderkey)::BIGINT AS orders FROM (SELECT * FROM customer WHERE c_custkey < 100) FULL JOIN (SELECT * FROM orders WHERE o_orderkey < 1000) ON c_custkey = o_custkey"),
    "join_right": (lambda spark, d: _keys(spark, d, "customer", "c_custkey < 100", "c_custkey").join(_keys(spark, d, "orders", "o_orderkey < 1000", "o_custkey", "o_orderkey"), F.col("c_custkey") == F.col("o_custkey"), "right").agg(F.count("c_custkey").alias("n"), F.count("o_orderkey").alias("orders")), "SELECT count(c_custkey)::BIGINT AS n, count(o_orderkey)::BIGINT AS orders FROM (SELECT * FROM customer WHERE c_custkey < 100) RIGHT JOIN (SELECT * FROM orders WHERE o_orderkey < 1000) ON c_custkey = o_custkey"),
    "join_dictionary": (lambda spark, d: dictionary.codes(load(spark, d, "customer", ["c_custkey", "c_name"]), "c_name", dictionary.table(load(spark, d, "customer"), "c_name")).select("c_custkey", "code"), "SELECT c_custkey, dense_rank() OVER (ORDER BY c_name) - 1 AS code FROM customer"),
    "join_address": (_address, "SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_quantity > 25 AND l_linenumber < 4"),
    "join_range": (_range, "SELECT count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate::DATE BETWEEN o_orderdate::DATE AND o_orderdate::DATE + 30"),
    "join_as_of": (_as_of, "WITH k AS (SELECT event_type, row_number() OVER (ORDER BY event_type) AS r FROM (SELECT DISTINCT event_type FROM events)), l AS (SELECT e.* FROM events e JOIN k USING (event_type) WHERE r = 1), r AS (SELECT user_id, ts, max(event_id) AS before_id FROM events e JOIN k USING (event_type) WHERE r = 2 GROUP BY ALL) SELECT l.event_id, r.before_id FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts"),
}
