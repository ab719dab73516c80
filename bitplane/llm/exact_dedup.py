"""Exact deduplication by tree-merged sorted runs of digests (DataFrame functions only).

Texts are read once, for rows of digest and identifier, which are stored.  Every leaf (a
hash range of document ids) sorts its rows by digest into a run with one entry a digest: the
identifier that stays and the number of rows.  In each round the runs of sixteen
neighbouring leaves are exchanged, four steps of a binomial tree at once, and merged
in digest order, entry by entry, until the root holds one run; sorted aggregation is the
merge, as the entries' best identifiers are structures, which Spark never hashes.  The entries with copies then
go back to the leaves that hold them.  Two rows are the same only if SHA-256, byte length and an independent 64-bit hash
all agree; that triple is the merge key, so identity is verified at every level.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Shelf, ascii_lower, leaf_count, leaf_of, merge_up

KEYS = ["__digest", "__bytes", "__check"]


def fingerprint(df: DataFrame, text_col: str = "text") -> DataFrame:
    norm = ascii_lower(F.coalesce(F.col(text_col), F.lit("")))
    return df.withColumn("__norm", norm).withColumns({
        "__digest": F.unhex(F.sha2("__norm", 256)),
        "__bytes": F.octet_length("__norm"),
        "__check": F.xxhash64(F.lit(17), F.col("__norm")),
    }).drop("__norm")


def groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest") -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256.

    Null texts count as empty.  A null id never wins over another id; if all ids
    of a group are null, keep_id is null and all its rows are kept.  Rows that
    repeat an id and a text each count in group_size and share their verdict.
    """
    spark = df.sparkSession
    leaves, shelf = leaf_count(spark), Shelf(spark, "exact")
    ids = fingerprint(df.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text")), "__text")
    rows = shelf.put(ids.select("__id", *KEYS, leaf_of(F.col("__id"), leaves).alias("__leaf")))
    runs = shelf.put(rows.groupBy(*KEYS, "__leaf").agg(best(F.col("__id"), keep).alias("__best"), F.count(F.lit(1)).alias("__n")))
    pick = F.max if keep == "largest" else F.min
    root = merge_up(runs, KEYS, leaves, [pick("__best").alias("__best"), F.sum("__n").alias("__n")])
    # One entry for each leaf that holds a copy: the rows of a hot digest meet their own leaf's entry.
    found = runs.select(*KEYS, "__leaf").join(root.where("__n > 1"), KEYS).select(*KEYS, "__leaf", F.col("__best.id").alias("__keep"), "__n")
    found = shelf.put(found)
    shelf.clear(rows, found)
    merged = rows.join(found, [*KEYS, "__leaf"], "left")
    winner = F.when(F.col("__n").isNull(), F.col("__id")).otherwise(F.col("__keep"))
    return merged.select(
        F.col("__id").alias(id_col),
        winner.alias("keep_id"),
        F.coalesce("__n", F.lit(1)).cast("long").alias("group_size"),
        F.col("__id").eqNullSafe(winner).alias("kept"),
        F.lower(F.hex("__digest")).alias("text_sha256"),
    )


def best(x: Column, keep: str) -> Column:
    """The identifier that stays, as a structure in which a null comes behind all others."""
    if keep == "largest":
        return F.max(F.struct(x.isNotNull().alias("known"), x.alias("id")))
    return F.min(F.struct(x.isNull().alias("unknown"), x.alias("id")))


def dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest") -> DataFrame:
    """The rows that stay, with their own columns; exact repeats of a row collapse.

    Of rows with equal text and equal id, one stays (which one is not defined
    where their other columns differ).
    """
    verdict = groups(df, id_col, text_col, keep).where("kept").groupBy(F.col(id_col).alias("__id"), F.col("text_sha256").alias("__sha")).agg(F.count(F.lit(1)).alias("__copies"))
    tagged = df.withColumn("__sha", F.sha2(ascii_lower(F.coalesce(F.col(text_col), F.lit(""))), 256))
    right = verdict.select(F.col("__id").alias("__kid"), F.col("__sha").alias("__ksha"), "__copies")
    on = F.col(id_col).eqNullSafe(F.col("__kid")) & (F.col("__sha") == F.col("__ksha"))
    staying = tagged.join(right, on, "inner").drop("__kid", "__ksha")
    single = staying.where("__copies = 1")
    repeated = staying.where("__copies > 1").dropDuplicates([id_col, "__sha"])
    return single.unionByName(repeated).select(*df.columns)
