"""What the encoded scan is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def scalar(df: DataFrame, condition: str | Column) -> DataFrame:
    """Columnar scan and generated filter code."""
    return df.where(condition).agg(F.count(F.lit(1)).alias("n"))


def boxed(df: DataFrame, col: str, test) -> DataFrame:
    """One boxed object a value, tested row by row in Python."""
    keep = F.udf(lambda x: x is not None and bool(test(x)), "boolean")
    return df.where(keep(F.col(col))).agg(F.count(F.lit(1)).alias("n"))


def arrow(df: DataFrame, col: str, op: str, constant, vectorised: bool = True) -> DataFrame:
    """Arrow buffers, by compute kernels or by an accessor a value."""
    tests = {"gt": pc.greater, "ge": pc.greater_equal, "eq": pc.equal, "lt": pc.less, "le": pc.less_equal}
    plain = {"gt": lambda x: x > constant, "ge": lambda x: x >= constant, "eq": lambda x: x == constant, "lt": lambda x: x < constant, "le": lambda x: x <= constant, "in": lambda x: x in constant}

    def run(batches):
        n = 0
        for b in batches:
            c = b.column(0)
            if not vectorised:
                n += sum(1 for x in c.to_pylist() if x is not None and plain[op](x))
            elif op == "in":
                n += pc.sum(pc.is_in(c, value_set=pa.array(constant, c.type))).as_py() or 0
            else:
                n += pc.sum(tests[op](c, pa.scalar(constant, c.type))).as_py() or 0
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    return df.select(col).mapInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def parquet_materialised(df: DataFrame, condition: str) -> DataFrame:
    """Values are decoded first, then filtered: a row number that the filter reads keeps it from reaching the file."""
    return df.withColumn("__at", F.monotonically_increasing_id()).where(f"({condition}) AND __at >= 0").agg(F.count(F.lit(1)).alias("n"))


def parquet_pushdown(df: DataFrame, condition: str) -> DataFrame:
    return df.where(condition).agg(F.count(F.lit(1)).alias("n"))


def dict_scan(df: DataFrame, col: str, values: list[str], dictionary: list[str]) -> DataFrame:
    """The predicate is resolved on the dictionary, codes are scanned unsliced."""
    codes = [i for i, v in enumerate(dictionary) if v in set(values)]
    return df.where(F.col(col).isin(codes)).agg(F.count(F.lit(1)).alias("n"))


def hash_in(df: DataFrame, col: str, keys: DataFrame, most: int = 1_000_000) -> DataFrame:
    """IN by a semi join on values; the key list is broadcast up to ``most`` keys."""
    small = keys.limit(most + 1).count() <= most
    keys = F.broadcast(keys) if small else keys
    return df.join(keys, col, "left_semi").agg(F.count(F.lit(1)).alias("n"))


def point_lookup(df: DataFrame, col: str, keys: list) -> DataFrame:
    """Equality on a few keys with pushdown into row-group statistics."""
    return df.where(F.col(col).isin(keys))


def numpy_codes(codes: np.ndarray, wanted: list[int]) -> int:
    return int(np.isin(codes, wanted).sum())
