"""The user-facing handle on an encoded dataset."""

from __future__ import annotations

import dataclasses

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..functions import metrics
from ..functions.bits import lit, positions, shl
from ..functions.codecs import Codec
from ..plans import binding, kernels, planner, predicates
from ..plans.predicates import Pred
from ..plans.spec import Manifest
from . import aggregate, encode, select, skipping


@dataclasses.dataclass
class SlicedTable:
    words: DataFrame
    manifest: Manifest
    base: DataFrame | None = None  # the addressed source, for late materialisation
    measured: dict[str, float] | None = None  # seconds by engine

    @classmethod
    def from_df(cls, df: DataFrame, codecs: dict[str, Codec | tuple[Codec, Column]], bias="global", block_size: int = 1024, widths=None, engine: str = "arrow", manifest: Manifest | None = None, common_base: bool = False, bloom: tuple[str, ...] = (), like: Manifest | None = None) -> SlicedTable:
        manifest = manifest or encode.plan(df, codecs, bias, block_size, widths, common_base, bloom, like)
        return cls(encode.to_words(df, codecs, manifest, engine), manifest, df)

    def where(self, pred: Pred | str, mode: str = "skip", in_strategy: str = "auto", engine: str = "catalyst", **kernel) -> Selection:
        """Rows of a predicate.  Parts that no encoded column can decide raise; see ``split``.

        The planner orders conjuncts by width where words are skipped and picks between planes and a hash set for IN
        lists; ``engine="auto"`` takes the fastest of a calibration (``calibrate``), generated code without one.
        """
        p = predicates.parse(pred) if isinstance(pred, str) else pred
        p = planner.order_conjuncts(predicates.normalise(p), self.manifest) if mode == "skip" else p
        engine = planner.kernel_for(self.measured) if engine == "auto" else engine
        node = binding.bind(p, self.manifest, in_strategy)
        every = None
        if engine == "numpy":
            masked = _numpy(self.words, self.manifest, node, kernel)
        else:
            words = skipping.zone_filter(self.words, self.manifest, node) if mode == "skip" else self.words
            mask = kernels.array_mask(node, self.manifest) if engine == "array" else kernels.catalyst(node, self.manifest, mode)
            masked, every = select.with_mask(words, mask), words.select(mask.alias("mask"))
        return Selection(masked, self, node, every)

    def calibrate(self, pred: Pred | str) -> dict[str, float]:
        """Times a count on both engines and remembers it for ``engine="auto"``."""
        self.measured = planner.calibrate(lambda engine: self.where(pred, engine=engine).count())
        return self.measured

    def all(self) -> Selection:
        return Selection(self.words.withColumn("mask", F.col("live")), self, ("and", []))

    def mask_each(self, preds: list[Pred | str]) -> DataFrame:
        """One mask column per predicate, from one scan."""
        nodes = [binding.bind(predicates.parse(p) if isinstance(p, str) else p, self.manifest) for p in preds]
        return self.words.select("*", *[kernels.catalyst(n, self.manifest, "oblivious").alias(f"mask{i}") for i, n in enumerate(nodes)])

    def filter_with_residual(self, pred: Pred | str, residual: str | None, cols: list[str]) -> DataFrame:
        """Encoded part first, then the rest on the rows fetched from the base table."""
        rows = select.late(self.where(pred).masked, self.base, self.manifest.block_size, self.base.columns)
        return (rows.where(residual) if residual else rows).select(*cols)

    def explain(self, pred: Pred | str) -> dict:
        """Predicted plane passes, operations and bytes: the same for any constant inside the domain."""
        node = binding.bind(predicates.parse(pred) if isinstance(pred, str) else pred, self.manifest)
        return planner.estimate(node, self.manifest)

    def memory_bytes(self) -> DataFrame:
        """Bytes by the size formula, from headers alone: one row a column."""
        parts = []
        for s in self.manifest.columns:
            parts.append(F.struct(F.lit(s.name).alias("column"), F.sum(F.col(s.header("bits")).cast("long") * 8 + F.when(F.col(s.header("v")).isNotNull(), 8).otherwise(0)).alias("bytes"), F.sum("live_rows").alias("rows")))
        got = self.words.withColumn("live_rows", F.bit_count("live").cast("long")).agg(F.array(*parts).alias("x"))
        return got.select(F.explode("x").alias("x")).select("x.*")

    def persist(self, level: StorageLevel = StorageLevel.MEMORY_AND_DISK) -> SlicedTable:
        self.words.persist(level)
        return self

    def unpersist(self) -> None:
        self.words.unpersist(blocking=True)

    def __enter__(self) -> SlicedTable:
        return self.persist()

    def __exit__(self, *_) -> None:
        self.unpersist()


def _numpy(words: DataFrame, manifest: Manifest, node: tuple, options: dict) -> DataFrame:
    schema = StructType([*words.schema.fields, StructField("mask", LongType())])
    names = words.columns

    def run(batches):
        for batch in batches:
            def column(name: str):
                a = batch.column(names.index(name))
                if name.endswith("__v"):
                    return None if a.null_count == len(a) else a.fill_null(-1).to_numpy(zero_copy_only=False)
                return a.fill_null(0).to_numpy(zero_copy_only=False)

            mask = kernels.numpy_mask(node, manifest, column, **options)
            out = pa.RecordBatch.from_arrays([*batch.columns, pa.array(mask)], [*names, "mask"])
            yield out.filter(pa.array(mask != 0))

    return words.mapInArrow(run, schema)


@dataclasses.dataclass
class Selection:
    masked: DataFrame
    table: SlicedTable
    node: tuple
    every: DataFrame | None = None  # the masks alone, empty ones too: a count need not compute them twice to drop those

    def count(self) -> DataFrame:
        return aggregate.count(self.masked if self.every is None else self.every)

    def summary(self, col: str) -> DataFrame:
        return aggregate.summary(self.masked, self.table.manifest[col])

    def group_sum(self, by: str, measure: str | None = None) -> DataFrame:
        return aggregate.group_sum(self.masked, self.table.manifest, by, measure)

    def distinct(self, col: str) -> DataFrame:
        return aggregate.distinct_codes(self.masked, self.table.manifest, col)

    def kth(self, col: str, k: int) -> int | None:
        return aggregate.kth(self.masked, self.table.manifest[col], k)

    def fetch(self, *cols: str, address: bool = False) -> DataFrame:
        return select.fetch(self.masked, self.table.manifest, list(cols) or [s.name for s in self.table.manifest.columns], address)

    def late(self, *cols: str) -> DataFrame:
        return select.late(self.masked, self.table.base, self.table.manifest.block_size, list(cols) or self.table.base.columns)

    def sample(self, share: float, seed: int = 0) -> Selection:
        """About ``share`` of the selected rows: each row's address is hashed, so a repeat gives the same rows."""
        pos = lambda i: F.col("block_id") * self.table.manifest.block_size + F.col("word_no") * 64 + i
        drawn = F.filter(positions(F.col("mask")), lambda i: F.pmod(F.xxhash64(F.lit(seed), F.col("file_id"), pos(i)), F.lit(1 << 30)) < int(share * (1 << 30)))
        mask = F.aggregate(drawn, lit(0), lambda m, i: m.bitwiseOR(shl(lit(1), i)))
        return Selection(select.with_mask(self.masked, mask), self.table, self.node)

    def row_ids(self) -> DataFrame:
        return select.row_ids(self.masked, self.table.manifest.block_size)


def footprint(manifest: Manifest) -> dict[str, float]:
    """Bytes a value and ratio to 32 bits, by column, at dataset-wide width."""
    return {s.name: metrics.bytes_per_value(s.planes) for s in manifest.columns}
