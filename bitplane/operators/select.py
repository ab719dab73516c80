"""From masks to rows: positions, decoding, late materialisation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import any_of, bit, lit, popcount, positions
from ..plans.spec import ColumnSpec, Manifest
from ..sources.tables import FILE, ROW


def with_mask(words: DataFrame, mask: Column) -> DataFrame:
    return words.withColumn("mask", mask).where("mask <> 0")


def row_ids(masked: DataFrame, block_size: int) -> DataFrame:
    """(file_id, row_index) of all set bits."""
    at = masked.select(FILE, "block_id", "word_no", F.explode(positions(F.col("mask"))).alias("pos"))
    return at.select(FILE, (F.col("block_id") * block_size + F.col("word_no") * 64 + F.col("pos")).alias(ROW))


def ordinal(spec: ColumnSpec, pos: Column) -> Column:
    """The ordinal at ``pos`` of a word: null where invalid."""
    bits = any_of([F.shiftleft(bit(F.col(spec.plane(j)), pos), j) for j in range(spec.planes)])
    if spec.planes == 64:  # the sum wraps around, which ANSI arithmetic forbids
        wide = F.when(bits < 0, bits.cast("decimal(20,0)") + F.lit(str(1 << 64)).cast("decimal(20,0)")).otherwise(bits.cast("decimal(20,0)"))
        raw = (wide + F.lit(spec.base).cast("decimal(20,0)")).cast("long")
    else:
        raw = bits + (lit(spec.base) if spec.literal else F.col(spec.header("bias")))
    if not spec.has_nulls:
        return raw
    return F.when(bit(F.coalesce(F.col(spec.header("v")), lit(-1)), pos) == 1, raw)


def decoded(spec: ColumnSpec, pos: Column) -> Column:
    """The value at ``pos`` of a word: null where invalid."""
    return spec.codec.value(ordinal(spec, pos))


def ordinals(masked: DataFrame, manifest: Manifest, cols: list[str]) -> DataFrame:
    """The selected rows' ordinals."""
    at = masked.withColumn("__pos", F.explode(positions(F.col("mask"))))
    return at.select(*[ordinal(manifest[c], F.col("__pos")).alias(c) for c in cols])


def fetch(masked: DataFrame, manifest: Manifest, cols: list[str], address: bool = False) -> DataFrame:
    """The selected rows' columns, read from their planes alone."""
    at = masked.withColumn("__pos", F.explode(positions(F.col("mask"))))
    out = [decoded(manifest[c], F.col("__pos")).alias(c) for c in cols]
    if address:
        out += [F.col(FILE), (F.col("block_id") * manifest.block_size + F.col("word_no") * 64 + F.col("__pos")).alias(ROW)]
    return at.select(*out)


#: Selected rows (16 bytes each) up to which their addresses go to the base table's readers, which then is not shuffled.
LATE_ROWS = 1_000_000


def late(masked: DataFrame, base: DataFrame, block_size: int, cols: list[str], most: int = LATE_ROWS) -> DataFrame:
    """Columns that were not encoded, from the addressed base table by row address.

    A count of the masks tells how many rows are asked for: few are broadcast, and the base table is read once where it lies;
    many are joined by shuffling both sides.
    """
    wanted = masked.agg(F.coalesce(F.sum(popcount(F.col("mask"))), lit(0))).first()[0]
    ids = row_ids(masked, block_size)
    return base.join(F.broadcast(ids) if wanted <= most else ids, [FILE, ROW]).select(*cols)
