"""Grouping, windows, sets and nested data around encoded filters."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codecs import DecimalCodec, IntCodec
from ..sources.tables import load_addressed
from . import dictionary
from .table import Selection, SlicedTable

KEY, MONEY = IntCodec(sql="bigint"), DecimalCodec(scale=2)


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


def selected(spark, d, table: str, where: str, codecs: dict, strings: tuple[str, ...] = ()) -> Selection:
    """The rows of an encoded filter, for the operators behind it."""
    df = load_addressed(spark, d, table)
    codecs = codecs | {c: dictionary.build(df, c) for c in strings}
    return SlicedTable.from_df(df, codecs).where(where)


def _lines(spark, d) -> DataFrame:
    return selected(spark, d, "lineitem", "l_quantity > 25", {"l_quantity": KEY, "l_extendedprice": MONEY}, ("l_returnflag", "l_linestatus")).fetch("l_returnflag", "l_linestatus", "l_extendedprice")


def _orders(spark, d, where: str, *cols: str, strings: tuple[str, ...] = ()) -> DataFrame:
    return selected(spark, d, "orders", where, {"o_orderkey": KEY, "o_custkey": KEY, "o_totalprice": MONEY}, strings).fetch(*cols, *strings)


def _grouping_sets(spark, d) -> DataFrame:
    flags = [F.col("l_returnflag"), F.col("l_linestatus")]
    return _lines(spark, d).groupingSets([flags, flags[:1], []], *flags).agg(F.count(F.lit(1)).alias("n"))


def _pivot(spark, d) -> DataFrame:
    p = _orders(spark, d, "o_totalprice > 50000", strings=("o_orderpriority", "o_orderstatus")).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return p.select("o_orderpriority", *[F.coalesce(F.col(s), F.lit(0)).cast("long").alias(f"n_{s.lower()}") for s in "FOP"])


def _ranks(spark, d) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc(cents("o_totalprice")), "o_orderkey")
    o = _orders(spark, d, "o_totalprice > 100000", "o_orderkey", "o_custkey", "o_totalprice")
    return o.select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(3).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


def _frames(spark, d) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = selected(spark, d, "events", "value > 5", {"event_id": KEY, "user_id": KEY, "value": MONEY}).fetch()
    return e.select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.sum(cents("value")).over(w.rowsBetween(-2, 0)).alias("last3"), F.sum(cents("value")).over(w.rangeBetween(-100, 0)).alias("near"), F.nth_value("event_id", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"))


def _sets(spark, d) -> DataFrame:
    codecs = {"l_quantity": KEY, "l_extendedprice": MONEY, "l_orderkey": KEY}
    a, b = (selected(spark, d, "lineitem", where, codecs).fetch("l_orderkey") for where in ("l_quantity > 45", "l_extendedprice > 90000"))
    parts = {"union": a.union(b).distinct(), "union_all": a.union(b), "intersect": a.intersect(b), "except": a.subtract(b), "except_all": a.exceptAll(b), "intersect_all": a.intersectAll(b)}
    out = None
    for k, x in parts.items():
        one = x.agg(F.count(F.lit(1)).alias("n"), F.sum("l_orderkey").alias("s")).withColumn("op", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out


def _json(spark, d) -> DataFrame:
    e = load_addressed(spark, d, "events", ["props", "event_id"])
    k = F.from_json("props", "k bigint")["k"]
    t = SlicedTable.from_df(e, {"k": (IntCodec(sql="bigint"), k), "event_id": IntCodec(sql="bigint")})
    return t.where("k BETWEEN 10 AND 40").fetch("event_id", "k")


def _arrays(spark, d) -> DataFrame:
    v = selected(spark, d, "embeddings", "label > 2", {"label": KEY}).late("label", "embedding")
    norm = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return v.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(norm), 3).alias("energy"))


SET = "SELECT '{}' AS op, count(*)::BIGINT AS n, sum(l_orderkey)::BIGINT AS s FROM (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45 {} SELECT l_orderkey FROM lineitem WHERE l_extendedprice > 90000)"

WORKLOADS = {
    "rollup": (lambda spark, d: _lines(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(cents("l_extendedprice")).alias("cents")), "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM lineitem WHERE l_quantity > 25 GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "cube": (lambda spark, d: _lines(spark, d).cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem WHERE l_quantity > 25 GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "grouping_sets": (_grouping_sets, "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem WHERE l_quantity > 25 GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())"),
    "pivot": (_pivot, "SELECT o_orderpriority, (count(*) FILTER (o_orderstatus = 'F'))::BIGINT AS n_f, (count(*) FILTER (o_orderstatus = 'O'))::BIGINT AS n_o, (count(*) FILTER (o_orderstatus = 'P'))::BIGINT AS n_p FROM orders WHERE o_totalprice > 50000 GROUP BY 1"),
    "window_rank": (_ranks, "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WHERE o_totalprice > 100000 WINDOW w AS (PARTITION BY o_custkey ORDER BY round(o_totalprice * 100)::BIGINT DESC, o_orderkey)"),
    "window_frames": (_frames, "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS next, (sum(c) OVER (w ROWS 2 PRECEDING))::BIGINT AS last3, (sum(c) OVER (w RANGE 100 PRECEDING))::BIGINT AS near, nth_value(event_id, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM (SELECT *, round(value * 100)::BIGINT AS c FROM events WHERE value > 5) WINDOW w AS (PARTITION BY user_id ORDER BY event_id)"),
    "set_ops": (_sets, " UNION ALL ".join(SET.format(k, o) for k, o in {"union": "UNION", "union_all": "UNION ALL", "intersect": "INTERSECT", "except": "EXCEPT", "except_all": "EXCEPT ALL", "intersect_all": "INTERSECT ALL"}.items())),
    "json_props": (_json, "SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events WHERE json_extract(props, '$.k')::BIGINT BETWEEN 10 AND 40"),
    "array_ops": (_arrays, "SELECT label, count(*)::BIGINT AS n, round(sum(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 3) AS energy FROM embeddings WHERE label > 2 GROUP BY label"),
    "agg_mixed": (lambda spark, d: _orders(spark, d, "o_custkey > 20", "o_custkey", "o_totalprice", strings=("o_orderpriority",)).groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("custs"), F.count_if(F.col("o_totalprice") > 100000).alias("big"), F.max(cents("o_totalprice")).alias("top")), "SELECT o_orderpriority, count(DISTINCT o_custkey)::BIGINT AS custs, (count(*) FILTER (o_totalprice > 100000))::BIGINT AS big, max(round(o_totalprice * 100)::BIGINT) AS top FROM orders WHERE o_custkey > 20 GROUP BY 1"),
}
