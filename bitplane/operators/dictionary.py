"""String dictionaries of bounded size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codecs import DictCodec

#: Codes up to which a dictionary is held as literals; beyond, the column stays plain or is joined to its codes.
MOST = 4096


class DictionaryTooLarge(ValueError):
    pass


def build(df: DataFrame, col: str, order: str = "sorted", most: int = MOST) -> DictCodec:
    """The distinct values, at most ``most``; ``arrival`` orders by first row address instead of by bytes."""
    if order == "sorted":
        rows = df.select(col).where(F.col(col).isNotNull()).distinct().limit(most + 1).collect()
        values = sorted((r[0] for r in rows), key=lambda v: v.encode())
    else:
        first = df.where(F.col(col).isNotNull()).groupBy(col).agg(F.min(F.struct("file_id", "row_index")).alias("at"))
        values = [r[0] for r in first.orderBy("at").limit(most + 1).collect()]
    if len(values) > most:
        raise DictionaryTooLarge(f"{col} has more than {most} values")
    return DictCodec(values=tuple(values), ordered=order == "sorted")


def codes(df: DataFrame, col: str, dictionary: DataFrame, out: str = "code") -> DataFrame:
    """Adds codes from a dictionary table (value, code) of any size; unknown strings give null."""
    return df.join(dictionary.select(F.col("value").alias(col), F.col("code").alias(out)), col, "left")


def table(df: DataFrame, col: str) -> DataFrame:
    """(value, code) without the driver: ranks add a range partition's place to the places before it."""
    from pyspark.sql import Window

    from ..sources.sliced import scratch

    values = df.select(F.col(col).alias("value")).where("value is not null").distinct()
    path = scratch(df.sparkSession, "ranges")  # stored, since two samples of the values may cut them at different places
    values.repartitionByRange("value").withColumn("part", F.spark_partition_id()).write.parquet(path)
    ranged = df.sparkSession.read.parquet(path)
    inner = ranged.withColumn("place", F.row_number().over(Window.partitionBy("part").orderBy("value")) - 1)
    sizes = ranged.groupBy("part").count()
    before = sizes.withColumn("before", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return inner.join(F.broadcast(before), "part").select("value", (F.col("before") + F.col("place")).cast("long").alias("code"))
