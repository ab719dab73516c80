"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary_path(name: str) -> str:
    """Place of a public tokenizer file; the folder is a setting, never copied."""
    import public_tokenizers

    return public_tokenizers.path(name)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, from the session; a local one only if unset (tests)."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        path = f"/tmp/bitplane-shared-{os.getpid()}"
        os.makedirs(path, exist_ok=True)
        return f"file://{path}"
    raise ValueError("set spark.checkpoint.dir to a folder that all executors share")


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh name below the shared folder."""
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write and read back: cuts the lineage and survives lost executors."""
    return Shelf(df.sparkSession, label).put(df)


class Shelf:
    """Stored intermediate tables of one operator, in one folder of the shared place.

    With ``rest``, the driver's memory is given back after every so many tables.
    """

    def __init__(self, spark: SparkSession, label: str, rest: int | None = None):
        self.spark, self.root, self.rest = spark, scratch(spark, label), rest
        self.held: list[tuple[DataFrame, str]] = []

    def put(self, df: DataFrame) -> DataFrame:
        """Written and read back, as ``stored``."""
        path = f"{self.root}/{len(self.held)}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.held.append((out, path))
        if self.rest and len(self.held) % self.rest == 0:
            driver_gives_back(self.spark)
        return out

    def clear(self, *keep: DataFrame) -> None:
        """Deletes all tables but those that a result still reads."""
        for df, path in self.held:
            if not any(df is k for k in keep):
                target = self.spark._jvm.org.apache.hadoop.fs.Path(path)
                target.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(target, True)


def give_back() -> None:
    """Returns what a Python worker has freed to the system: Arrow's pool and malloc keep it for a process that may long be idle."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)


def driver_gives_back(spark: SparkSession) -> str:
    """Returns what the driver has freed to the system; what its JVM says of its native memory, empty if it can't.

    Many short queries leave plans, shuffles and broadcasts that the driver drops only when it happens to collect
    garbage, a heap grown for them, and freed native memory in the C library's arenas, one or more a thread.
    """
    gc.collect()  # frames in cycles hold their plans in the JVM
    give_back()
    jvm, new_array = spark._jvm, spark.sparkContext._gateway.new_array
    jvm.System.gc()
    with contextlib.suppress(Exception):  # JVMs from 17 on, and glibc, have the command
        kinds, values = new_array(jvm.Class, 4), new_array(jvm.Object, 4)
        for i, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[i] = jvm.Class.forName(kind)
        values[0], values[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        # The server's own class is hidden, its interface is not.
        call = jvm.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds)
        return str(call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), values))
    return ""


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A function for mapInArrow that gives freed memory back when its task ends."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only.  Pure ASCII strings take the byte-wise built-in."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def leaf_count(spark: SparkSession) -> int:
    """Virtual leaves over which the rows of one key are spread."""
    return max(32, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def leaf_of(row_id: Column, leaves: int) -> Column:
    return F.pmod(F.xxhash64(row_id), F.lit(leaves)).cast("int")


def hand_down(rows: DataFrame, table: DataFrame, keys: list[str], how: str = "inner", hint: str | None = None) -> DataFrame:
    """Joins ``table``, with one row a key, to ``rows`` in which one key may have a third of all rows.

    ``rows`` has ``__leaf``.  The table meets one row for each key and leaf first (at most as many a key as
    there are leaves) and the rows of a leaf then meet their own copy, so a hot key is spread over all leaves.
    ``hint`` names the strategy of both joins.
    """
    hinted = (lambda df: df.hint(hint)) if hint else (lambda df: df)
    held = rows.groupBy(*keys, "__leaf").agg(F.count(F.lit(1)).alias("__held"))
    return rows.join(hinted(held.join(hinted(table), keys).drop("__held")), [*keys, "__leaf"], how)


def merge_up(runs: DataFrame, keys: list[str], leaves: int, merge: list[Column], fan: int = 16) -> DataFrame:
    """One row a key from the runs of all leaves: in each round the runs of ``fan`` neighbouring leaves merge.

    A round with a fan of 16 does four rounds of a binomial tree at once.  No task meets more than ``fan`` rows of a key.
    """
    level, width = runs, leaves
    while width > 1:
        width = -(-width // fan)
        level = level.withColumn("__leaf", F.expr(f"cast(__leaf div {fan} as int)")).groupBy(*keys, "__leaf").agg(*merge)
    return level.drop("__leaf")


def gather_scatter(rows: DataFrame, keys: list[str], leaves: int, first: list[Column], merge: list[Column], keep: Column, how: str = "inner", hint: str | None = None) -> DataFrame:
    """Aggregates per key over a tree of leaves and hands the results that satisfy ``keep`` back to the rows.

    ``rows`` has ``keys`` and ``__leaf``, and is read several times: store what is dear to make.
    ``first`` builds a leaf's run, ``merge`` combines runs; both name the same columns.
    """
    runs = rows.groupBy(*keys, "__leaf").agg(*first)
    return hand_down(rows, merge_up(runs, keys, leaves, merge).where(keep), keys, how, hint)
