"""Plain tables in, with stable row addresses."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FILE, ROW = "file_id", "row_index"


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def addressed(spark: SparkSession, path: str, columns: list[str] | None = None) -> DataFrame:
    """The table with file_id and row_index of every row: the same after a retry and under any split."""
    df = spark.read.parquet(path)
    cols = columns or df.columns
    return df.select(*cols, F.xxhash64(F.col("_metadata.file_path")).alias(FILE), F.col("_metadata.row_index").alias(ROW))


def load_addressed(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    return addressed(spark, f"{sf_dir}/{name}.parquet", columns)


def read_any(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options: str) -> DataFrame:
    """parquet, orc, csv, json, text (and avro where the session has it)."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, fmt: str, path: str, mode: str = "error", partition_by: list[str] | None = None, **options: str) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
