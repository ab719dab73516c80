"""SQL-visible functions: plane predicates on arrays, set positions, word packing."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def _positions(mask: int):
    x = (mask or 0) & ((1 << 64) - 1)
    while x:
        low = x & -x
        yield (low.bit_length() - 1,)
        x ^= low


@F.udtf(returnType="pos: int")
class SetPositions:
    """The set bits of a mask, ascending."""

    def eval(self, mask: int):
        yield from _positions(mask)


@F.udtf(returnType="pos: int, value: bigint")
class DecodeWord:
    """Values at the set bits of ``mask`` from an array of planes and a bias."""

    def eval(self, planes: list, bias: int, mask: int):
        for (p,) in _positions(mask):
            yield p, bias + sum(((w >> p) & 1) << j for j, w in enumerate(planes))


def slice_agg(pos, value):
    """Grouped aggregate: planes of the (at most 64) values of a word; the check on the packers."""

    def run(pos, value):
        top = max(1, int(value.max()).bit_length()) if len(value) else 1
        out = [0] * top
        for p, v in zip(pos.tolist(), value.tolist()):
            for j in range(top):
                out[j] |= (int(v) >> j & 1) << int(p)
        return [x - (1 << 64) if x >> 63 else x for x in out]

    return F.pandas_udf(run, "array<bigint>", F.PandasUDFType.GROUPED_AGG)(pos, value)


FUNCTIONS = {
    "bp_eq": "aggregate(sequence(0, size(ps) - 1), -1L, (g, j) -> g & ~(ps[j] ^ (-(shiftrightunsigned(c, j) & 1L))))",
    "bp_gt": "aggregate(sequence(0, size(ps) - 1), 0L, (g, j) -> (ps[j] & ~(-(shiftrightunsigned(c, j) & 1L))) | (g & (ps[j] ^ ~(-(shiftrightunsigned(c, j) & 1L)))))",
    "bp_ge": "aggregate(sequence(0, size(ps) - 1), -1L, (g, j) -> (ps[j] & ~(-(shiftrightunsigned(c, j) & 1L))) | (g & (ps[j] ^ ~(-(shiftrightunsigned(c, j) & 1L)))))",
}


def register(spark: SparkSession) -> None:
    """bp_eq, bp_gt, bp_ge (planes, constant), bp_between (planes, lo, hi), bp_in (planes, constants); set_positions, decode_word."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(ps ARRAY<BIGINT>, c BIGINT) RETURNS BIGINT RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bp_between(ps ARRAY<BIGINT>, lo BIGINT, hi BIGINT) RETURNS BIGINT RETURN bp_ge(ps, lo) & ~bp_gt(ps, hi)")
    one = FUNCTIONS["bp_eq"].replace("c, j", "x, j")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bp_in(ps ARRAY<BIGINT>, cs ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(cs, 0L, (m, x) -> m | ({one}))")
    spark.udtf.register("set_positions", SetPositions)
    spark.udtf.register("decode_word", DecodeWord)
