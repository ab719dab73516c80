"""Aggregates from planes and masks, without decoding rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import lit, popcount
from ..plans.kernels import validity
from ..plans.spec import ColumnSpec, Manifest
from .select import ordinals

WIDE = "decimal(38,0)"


def covered(spec: ColumnSpec) -> Column:
    return F.col("mask").bitwiseAND(validity(spec, F.col("live")))


def count(masked: DataFrame) -> DataFrame:
    return masked.agg(F.coalesce(F.sum(popcount(F.col("mask"))), lit(0)).alias("n"))


def linear(spec: ColumnSpec) -> None:
    if not spec.codec.linear:
        raise ValueError(f"{spec.name}: its ordinals keep order only; fetch the rows to sum them")


def sum_parts(spec: ColumnSpec, prefix: str) -> list[Column]:
    """A BIGINT count a plane, and the bias times the rows."""
    m = covered(spec)
    parts = [F.sum(popcount(F.col(spec.plane(j)).bitwiseAND(m))).alias(f"{prefix}__c{j}") for j in range(spec.planes)]
    bias = lit(spec.base) if spec.literal else F.col(spec.header("bias"))
    parts.append(F.sum(popcount(m)).alias(f"{prefix}__n"))
    parts.append(F.sum(bias.cast(WIDE) * popcount(m).cast("decimal(4,0)")).alias(f"{prefix}__b"))
    return parts


def sum_of(spec: ColumnSpec, prefix: str) -> Column:
    """The exact sum of ordinals, null if no row has a value."""
    total = F.col(f"{prefix}__b").cast(WIDE)
    for j in range(spec.planes):
        total = (total + F.col(f"{prefix}__c{j}").cast(WIDE) * F.lit(str(1 << j)).cast("decimal(20,0)")).cast(WIDE)
    return F.when(F.col(f"{prefix}__n") > 0, total)


def extreme(spec: ColumnSpec, largest: bool) -> Column:
    """A word's greatest (least) selected ordinal: candidates shrink plane by plane from the top."""
    start = covered(spec)
    planes = F.array(*[F.struct(F.col(spec.plane(j)).alias("p"), lit(1 << j if j < 63 else -(1 << 63)).alias("w")) for j in reversed(range(spec.planes))])

    def step(acc: Column, x: Column) -> Column:
        hit = acc["m"].bitwiseAND(x["p"] if largest else F.bitwise_not(x["p"]))
        taken = hit != 0
        gain = F.when(taken, x["w"] if largest else lit(0)).otherwise(lit(0) if largest else x["w"])
        return F.struct(F.when(taken, hit).otherwise(acc["m"]).alias("m"), acc["v"].bitwiseOR(gain).alias("v"))

    got = F.aggregate(planes, F.struct(start.alias("m"), lit(0).alias("v")), step)["v"]
    bias = lit(spec.base) if spec.literal else F.col(spec.header("bias"))
    return F.when(start != 0, got + bias)


def summary(masked: DataFrame, spec: ColumnSpec) -> DataFrame:
    """count, sum, avg (of linear codecs) as one row of n, sum_ord, plus min_ord and max_ord."""
    if spec.planes > 62:
        raise ValueError(f"{spec.name}: too wide for extremes by planes; fetch the rows")
    linear(spec)
    got = masked.agg(*sum_parts(spec, "s"), F.min(extreme(spec, False)).alias("min_ord"), F.max(extreme(spec, True)).alias("max_ord"))
    return got.select(F.coalesce("s__n", lit(0)).alias("n"), sum_of(spec, "s").alias("sum_ord"), "min_ord", "max_ord")


def second_moment(masked: DataFrame, spec: ColumnSpec) -> DataFrame:
    """n, sum and sum of squares of the ordinals above the base, from counts of plane pairs (literal biases)."""
    linear(spec)
    if not spec.literal or spec.planes > 24:
        raise ValueError("pairs of planes need a literal bias and at most 24 planes")
    m = covered(spec)
    pairs = [(i, j) for i in range(spec.planes) for j in range(i, spec.planes)]
    aggs = [F.sum(popcount(F.col(spec.plane(i)).bitwiseAND(F.col(spec.plane(j))).bitwiseAND(m))).alias(f"c{i}_{j}") for i, j in pairs]
    got = masked.agg(F.sum(popcount(m)).alias("n"), *aggs)
    def weight(i: int, j: int) -> Column:
        return F.lit(str((1 if i == j else 2) << (i + j))).cast(WIDE)
    squares = sum((F.col(f"c{i}_{j}").cast("decimal(19,0)") * weight(i, j) for i, j in pairs[1:]), F.col("c0_0").cast("decimal(19,0)") * weight(0, 0))
    firsts = sum((F.col(f"c{j}_{j}").cast("decimal(19,0)") * F.lit(str(1 << j)).cast("decimal(19,0)") for j in range(1, spec.planes)), F.col("c0_0").cast("decimal(19,0)") * 1)
    return got.select("n", firsts.cast(WIDE).alias("sum_above"), squares.cast(WIDE).alias("sum_squares_above"))


def kth(masked: DataFrame, spec: ColumnSpec, k: int, step: int = 4) -> int | None:
    """The k-th smallest selected ordinal (from 0), by counting ``step`` planes a job from the top down; literal biases."""
    if not spec.literal:
        raise ValueError("order statistics need a literal bias")
    prefix, left = 0, k
    j = spec.planes
    while j > 0:
        take = min(step, j)
        m = covered(spec)
        for i in range(j, spec.planes):
            p = F.col(spec.plane(i))
            m = m.bitwiseAND(p if prefix >> (i - j) & 1 else F.bitwise_not(p))
        aggs = []
        within = masked.withColumn("__within", m).where("__within <> 0")
        for v in range(1 << take):
            b = F.col("__within")
            for t in range(take):
                p = F.col(spec.plane(j - take + t))
                b = b.bitwiseAND(p if v >> t & 1 else F.bitwise_not(p))
            aggs.append(F.coalesce(F.sum(popcount(b)), lit(0)).alias(f"n{v}"))
        counts = within.agg(*aggs).first()
        for v, n in enumerate(counts):
            if left < n:
                break
            left -= n
        else:
            return None
        prefix, j = prefix << take | v, j - take
    return prefix + spec.base


def equal_code(spec: ColumnSpec, k: int) -> Column:
    m = covered(spec)
    for j in range(spec.planes):
        p = F.col(spec.plane(j))
        m = m.bitwiseAND(p if (k - spec.base) >> j & 1 else F.bitwise_not(p))
    return m


#: Codes up to which grouping and distinct make one mask a code; beyond, the rows' ordinals are fetched.
CODES = 1024


def few_codes(spec: ColumnSpec) -> list[int] | None:
    """The ordinals a column can hold, if they are known, not too many, and laid out on a literal bias."""
    if not spec.literal or spec.lo is None or spec.hi - spec.lo >= CODES:
        return None
    return list(range(spec.lo, spec.hi + 1))


def group_sum(masked: DataFrame, manifest: Manifest, by: str, measure: str | None = None) -> DataFrame:
    """Per value of ``by``: n and the exact sum of ``measure``'s ordinals (null without values); rows with a null ``by`` are left out.

    One mask a code where these are few, else the ordinals of the selected rows are grouped.
    """
    g = manifest[by]
    if measure is not None:
        linear(manifest[measure])
    if (codes := few_codes(g)) is None:
        rows = ordinals(masked, manifest, list({by: 0} | ({} if measure is None else {measure: 0}))).where(F.col(by).isNotNull())
        sums = [] if measure is None else [F.sum(F.col(measure).cast(WIDE)).alias("sum_ord")]
        out = rows.groupBy(by).agg(F.count(F.lit(1)).alias("n"), *sums)
        return out.select(g.codec.value(F.col(by)).alias(by), "n", *(["sum_ord"] if sums else []))
    masks = F.array(*[F.struct(lit(k).alias("k"), equal_code(g, k).alias("m")) for k in codes])
    split = masked.withColumn("__g", F.explode(masks)).where("__g.m <> 0").withColumn("mask", F.col("__g.m"))
    n = F.sum(popcount(F.col("mask"))).alias("n")
    if measure is None:
        return split.groupBy("__g.k").agg(n).select(g.codec.value(F.col("k")).alias(by), "n")
    s = manifest[measure]
    out = split.groupBy("__g.k").agg(n, *sum_parts(s, "s"))
    return out.select(g.codec.value(F.col("k")).alias(by), "n", sum_of(s, "s").alias("sum_ord"))


def distinct_codes(masked: DataFrame, manifest: Manifest, col: str) -> DataFrame:
    """Values present among the selected rows: by one mask a code where these are few, else from the rows' ordinals."""
    spec = manifest[col]
    if (codes := few_codes(spec)) is None:
        found = ordinals(masked, manifest, [col]).where(F.col(col).isNotNull()).distinct()
        return found.select(spec.codec.value(F.col(col)).alias(col))
    seen = masked.agg(*[F.coalesce(F.bool_or(equal_code(spec, k) != 0), F.lit(False)).alias(f"k{k - spec.lo}") for k in codes])
    flags = F.array(*[F.struct(lit(k).alias("k"), F.col(f"k{k - spec.lo}").alias("seen")) for k in codes])
    return seen.select(F.explode(flags).alias("x")).where("x.seen").select(spec.codec.value(F.col("x.k")).alias(spec.name))
