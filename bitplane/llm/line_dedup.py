"""Line deduplication (DataFrame functions only).

Lines are exploded with their position and a 128-bit hash of the normalised
line; hashes found in enough documents lose their lines everywhere but in the
smallest document, and the rest of each document is put together by position.
Texts are read twice: once for the hashes and positions of their lines, which are stored and are all that is
shuffled by line, and once to be put together again; texts move once, by document.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Shelf, ascii_lower, gather_scatter, leaf_count, leaf_of

#: Fixed value: the stripped characters, space and U+0009 to U+000D.
BLANKS = " \t\n\x0b\x0c\r"


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(BLANKS)))


def dedup_lines(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 10, min_docs: int = 2) -> DataFrame:
    """One row per input row: id, n_lines, n_dropped, and ``kept_text``.

    A null or empty text is one empty line.  Rows without id count as one
    document that comes after all others.  Rows that repeat an id belong to one
    document when holders are counted, and each is rebuilt from its own lines.
    """
    spark = df.sparkSession
    leaves, shelf = leaf_count(spark), Shelf(spark, "lines")
    text = F.coalesce(F.col(text_col), F.lit(""))
    docs = df.select(F.col(id_col).alias("__id"), text.alias("__text")).withColumn("__row", F.xxhash64(F.lit(3), F.col("__text")))
    lines = docs.select("__id", "__row", F.posexplode(F.split("__text", "\n", -1)).alias("__pos", "__line")).withColumn("__key", line_key(F.col("__line")))
    long_enough = lines.where(F.char_length("__key") >= min_chars).select(
        "__id", "__row", "__pos", F.xxhash64("__key").alias("__h1"), F.xxhash64(F.lit(11), F.col("__key")).alias("__h2"), leaf_of(F.col("__id"), leaves).alias("__leaf")
    )
    long_enough = shelf.put(long_enough)
    keys = ["__h1", "__h2"]
    # A leaf holds all rows of an id, so distinct ids add up over leaves; for two documents the extremes suffice.
    first = [F.min("__id").alias("__lo"), F.max("__id").alias("__hi"), F.max(F.col("__id").isNull()).alias("__none")]
    merge = [F.min("__lo").alias("__lo"), F.max("__hi").alias("__hi"), F.max("__none").alias("__none")]
    if min_docs == 2:
        keep = (F.col("__lo") != F.col("__hi")) | (F.col("__none") & F.col("__lo").isNotNull())
    else:
        first.append((F.count_distinct("__id") + F.max(F.col("__id").isNull().cast("long"))).alias("__docs"))
        merge.append(F.sum("__docs").alias("__docs"))
        keep = F.col("__docs") >= min_docs
    found = gather_scatter(long_enough, keys, leaves, first, merge, keep)
    gone = found.where(~F.col("__id").eqNullSafe(F.col("__lo"))).groupBy("__id", "__row").agg(F.collect_set("__pos").alias("__gone"))
    marked = shelf.put(gone.select(F.col("__id").alias("__gid"), F.col("__row").alias("__grow"), "__gone"))
    shelf.clear(marked)
    joined = docs.join(marked, F.col("__id").eqNullSafe(F.col("__gid")) & (F.col("__row") == F.col("__grow")), "left")
    parts = F.split("__text", "\n", -1)
    stay = F.array_except(F.sequence(F.lit(0), F.size("__parts") - 1), F.col("__gone"))
    out = joined.withColumn("__parts", parts)
    kept = F.when(F.col("__gone").isNull(), F.col("__text")).otherwise(F.array_join(F.transform(stay, lambda i: F.get(F.col("__parts"), i)), "\n"))
    return out.select(
        F.col("__id").alias(id_col),
        F.size("__parts").cast("long").alias("n_lines"),
        F.coalesce(F.size("__gone"), F.lit(0)).cast("long").alias("n_dropped"),
        kept.alias("kept_text"),
    )
