"""Rows to bit planes.

``to_words`` gives one row for 64 source rows, with one BIGINT column per plane, so
that column pruning is plane pruning.  Its Arrow engine is narrow: a block's rows are
neighbours in their file, and a block that a split cuts in two is two sets of
word rows with disjoint live bits.  Its Catalyst engine packs with bit_or
aggregates and is the check on the other.  ``to_blocks`` gives one row a block.
"""

from __future__ import annotations

import dataclasses
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, ByteType, IntegerType, LongType, StructField, StructType

from ..functions.bits import bit_width, lit, shl
from ..functions.codecs import Codec
from ..functions.metrics import width
from ..plans import blooms
from ..plans.spec import SCOPES, ColumnSpec, Manifest
from ..sources.tables import FILE, ROW

BIG = np.iinfo(np.int64).max
FEW_FILES = 1_000_000


def plan(df: DataFrame, codecs: dict[str, Codec | tuple[Codec, Column]], bias: str | dict[str, str] = "block", block_size: int = 1024, widths: dict[str, str | int] | None = None, common_base: bool = False, bloom: tuple[str, ...] = (), like: Manifest | None = None) -> Manifest:
    """One aggregate finds every column's ordinal range, null count and the plane count that always suffices.

    A codec may come with the expression it encodes.  ``common_base`` gives literal biases one base, for column comparisons.
    Columns in ``bloom`` get a filter in the header of each word.  ``like`` takes biases and sizes from a dataset that the rows
    are to be appended to, and fails if its literal bases cannot hold them.  ``declare`` needs no scan.
    """
    if like is not None:
        bias, block_size = {s.name: s.bias for s in like.columns}, like.block_size
        widths, bloom = {s.name: s.width for s in like.columns}, tuple(s.name for s in like.columns if s.bloom)
    if block_size % 64 or block_size < 64:
        raise ValueError("blocks hold a multiple of 64 rows")
    scopes = {c: bias if isinstance(bias, str) else bias.get(c, "block") for c in codecs}
    for c, s in scopes.items():
        if s not in SCOPES:
            raise ValueError(f"{c}: no bias scope {s!r}")
    cols = {c: ordinal(c, k) for c, k in codecs.items()}
    aggs = [f(x).alias(f"{c}__{n}") for c, x in cols.items() for f, n in ((F.min, "lo"), (F.max, "hi"), (F.count, "n"))]
    got = df.agg(F.count(F.lit(1)).alias("rows"), *aggs).first()
    lows = [got[f"{c}__lo"] for c in codecs if got[f"{c}__lo"] is not None]
    out = []
    for c, k in codecs.items():
        lo, hi, scope = got[f"{c}__lo"], got[f"{c}__hi"], scopes[c]
        if scope == "none" and (lo or 0) < 0:
            raise ValueError(f"{c}: negative values need a bias")
        base = 0 if scope == "none" or lo is None else min(lows) if common_base else lo
        if like is not None and like[c].literal:
            base, scope = like[c].base, like[c].bias
            if lo is not None and lo < base:
                raise ValueError(f"{c}: {lo} is below the dataset's base {base}; encode it anew, or with a block bias")
        planes = width((hi - base) if lo is not None else 0)
        if planes == 64 and scope in ("block", "file"):
            scope = "global"  # a difference of 64 bits overflows in per-block arithmetic, not as a literal
        fixed = (widths or {}).get(c, "block")
        if isinstance(fixed, int):
            if fixed < planes:
                raise ValueError(f"{c}: {planes} planes do not fit in {fixed}")
            planes = fixed
        out.append(ColumnSpec(c, k[0] if isinstance(k, tuple) else k, scope, planes, base if scope in ("none", "global") else 0, lo, hi, fixed, got[f"{c}__n"] < got["rows"], c in bloom))
    return Manifest(tuple(out), block_size, got["rows"])


def declare(codecs: dict[str, Codec | tuple[Codec, Column]], planes: dict[str, int], bias: str | dict[str, str] = "block", bases: dict[str, int] | None = None, block_size: int = 1024, bloom: tuple[str, ...] = ()) -> Manifest:
    """A manifest without a scan: plane counts (and literal bases) are stated, and packing fails where they do not hold.

    Bounds become known when the words are written (sources.sliced).
    """
    cols = [ColumnSpec(c, k[0] if isinstance(k, tuple) else k, bias if isinstance(bias, str) else bias.get(c, "block"), planes[c], (bases or {}).get(c, 0), bloom=c in bloom) for c, k in codecs.items()]
    return Manifest(tuple(cols), block_size).open()


def ordinal(name: str, codec: Codec | tuple[Codec, Column]) -> Column:
    return codec[0].ordinal(codec[1]) if isinstance(codec, tuple) else codec.ordinal(F.col(name))


def with_ordinals(df: DataFrame, codecs: dict[str, Codec | tuple[Codec, Column]], manifest: Manifest, keep: list[str] = ()) -> DataFrame:
    """file_id, row_index, one BIGINT a column; per-file biases are joined in where they are asked for."""
    out = df.select(FILE, ROW, *keep, *[ordinal(c, k).alias(c) for c, k in codecs.items()])
    per_file = [s for s in manifest.columns if s.bias == "file"]
    if per_file:
        lows = out.groupBy(FILE).agg(*[F.min(s.name).alias(f"{s.name}__file_bias") for s in per_file])
        # One row a file, of which the driver holds the listing; beyond so many files they are joined by shuffling.
        out = out.join(F.broadcast(lows) if len(df.inputFiles()) <= FEW_FILES else lows, FILE).sortWithinPartitions(FILE, ROW)  # a join drops the order asked for below it
    return out


def header_fields(spec: ColumnSpec) -> list[tuple[str, str]]:
    return [(spec.header("bits"), "byte"), (spec.header("bias"), "long"), (spec.header("mn"), "long"), (spec.header("mx"), "long"), (spec.header("v"), "long")]


def words_schema(manifest: Manifest) -> StructType:
    kinds = {"byte": ByteType(), "long": LongType(), "int": IntegerType()}
    fields = [(FILE, "long"), ("block_id", "long"), ("word_no", "int"), ("n", "int"), ("live", "long")]
    for s in manifest.columns:
        fields += header_fields(s) + [(f, "long") for f in blooms.names(s)] + [(s.plane(j), "long") for j in range(s.planes)]
    return StructType([StructField(n, kinds[k]) for n, k in fields])


@dataclasses.dataclass
class Packed:
    """Blocks of a stretch of rows: dense arrays of blocks x block size."""

    file: np.ndarray
    block: np.ndarray
    live: np.ndarray
    columns: dict


def pack(file: np.ndarray, row: np.ndarray, values: dict[str, tuple[np.ndarray, np.ndarray]], file_bias: dict[str, np.ndarray], manifest: Manifest) -> Packed:
    size = manifest.block_size
    block, pos = row // size, row % size
    new = np.r_[True, (file[1:] != file[:-1]) | (block[1:] != block[:-1])]
    seg = np.cumsum(new) - 1
    first = np.flatnonzero(new)
    n, at = len(first), seg * size + pos
    live = np.zeros(n * size, np.uint8)
    live[at] = 1
    out = {}
    for s in manifest.columns:
        x, ok = values[s.name]
        low = np.minimum.reduceat(np.where(ok, x, BIG), first)
        high = np.maximum.reduceat(np.where(ok, x, -BIG - 1), first)
        some = np.logical_or.reduceat(ok, first)
        low, high = np.where(some, low, 0), np.where(some, high, 0)
        bias = low if s.bias == "block" else np.where(some, file_bias[s.name][first], 0) if s.bias == "file" else np.full(n, s.base)
        dense = np.zeros(n * size, np.uint64)
        dense[at[ok]] = (x[ok].view(np.uint64) - bias.view(np.uint64)[seg[ok]])
        top = np.where(some, high.view(np.uint64) - bias.view(np.uint64), np.uint64(0))
        bits = np.maximum(1, np.searchsorted(np.uint64(1) << np.arange(64, dtype=np.uint64), top, side="right"))
        if len(bits) and bits.max() > s.planes:
            raise ValueError(f"{s.name}: a block needs {bits.max()} planes, the manifest has {s.planes}")
        if s.width != "block":
            bits = np.full(n, s.planes)
        valid = np.zeros(n * size, np.uint8)
        valid[at[ok]] = 1
        nulls = np.logical_or.reduceat(~ok, first)
        planes = [np.packbits((dense >> np.uint64(j) & np.uint64(1)).astype(np.uint8), bitorder="little") for j in range(s.planes)]
        filters = blooms.build(x[ok], at[ok] // 64, n * size // 64) if s.bloom else None
        out[s.name] = (bits, bias, low, high, some, nulls, np.packbits(valid, bitorder="little"), planes, filters)
    return Packed(file[first], block[first], np.packbits(live, bitorder="little"), out)


def stretches(batches: Iterator[pa.RecordBatch], manifest: Manifest, rows: int = 1 << 16) -> Iterator[Packed]:
    """Packs whole blocks; the rows of an unfinished one wait for the next batch."""
    held: list[pa.RecordBatch] = []

    def arrays(table: pa.Table) -> Packed:
        cols = {c: table[c].combine_chunks() for c in table.column_names}
        cols = {c: (a.chunk(0) if isinstance(a, pa.ChunkedArray) else a) for c, a in cols.items()}
        values = {s.name: (cols[s.name].fill_null(0).to_numpy(zero_copy_only=False), cols[s.name].is_valid().to_numpy(zero_copy_only=False)) for s in manifest.columns}
        biases = {s.name: cols[f"{s.name}__file_bias"].fill_null(0).to_numpy(zero_copy_only=False) for s in manifest.columns if s.bias == "file"}
        return pack(cols[FILE].to_numpy(), cols[ROW].to_numpy(), values, biases, manifest)

    def table_of(parts: list[pa.RecordBatch]) -> pa.Table:
        return pa.Table.from_batches(parts)

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        if sum(b.num_rows for b in held) < rows:
            continue
        table = table_of(held)
        key = table[ROW].to_numpy() // manifest.block_size
        files = table[FILE].to_numpy()
        cut = int(np.flatnonzero((key != key[-1]) | (files != files[-1]))[-1]) + 1 if (key[0] != key[-1] or files[0] != files[-1]) else 0
        if cut:
            yield arrays(table.slice(0, cut))
            held = table.slice(cut).combine_chunks().to_batches()
    if held:
        yield arrays(table_of(held))


def to_words(df: DataFrame, codecs: dict[str, Codec | tuple[Codec, Column]], manifest: Manifest, engine: str = "arrow") -> DataFrame:
    """``df`` needs file_id and row_index (sources.tables.addressed)."""
    rows = with_ordinals(df, codecs, manifest)
    if engine == "catalyst":
        if any(s.bloom for s in manifest.columns):
            raise ValueError("the aggregating encoder builds no Bloom filters")
        return _words_by_aggregates(rows, manifest)
    schema = words_schema(manifest)
    names = schema.fieldNames()
    per = manifest.block_size // 64

    def run(batches: Iterator[pa.RecordBatch]):
        for p in stretches(batches, manifest):
            live = p.live.view("<i8")
            keep = np.flatnonzero(live)
            block = keep // per
            count = np.bincount(block, np.bitwise_count(live[keep].view(np.uint64)), len(p.block)).astype(np.int32)
            cols = [pa.array(p.file[block]), pa.array(p.block[block]), pa.array((keep % per).astype(np.int32)), pa.array(count[block]), pa.array(live[keep])]
            for s in manifest.columns:
                bits, bias, low, high, some, nulls, valid, planes, filters = p.columns[s.name]
                cols += [pa.array(bits[block].astype(np.int8)), pa.array(bias[block].astype(np.int64))]
                cols += [pa.array(x[block], mask=~some[block]) for x in (low, high)]
                cols.append(pa.array(valid.view("<i8")[keep], mask=~nulls[block]))
                if s.bloom:
                    cols += [pa.array(f[keep]) for f in filters]
                cols += [pa.array(q.view("<i8")[keep]) for q in planes]
            yield pa.RecordBatch.from_arrays(cols, names)

    return rows.mapInArrow(run, schema)


def _words_by_aggregates(rows: DataFrame, manifest: Manifest) -> DataFrame:
    size = manifest.block_size
    pos = F.col(ROW) % size
    rows = rows.withColumns({"block_id": F.expr(f"{ROW} div {size}"), "word_no": F.floor(pos / 64).cast("int"), "__pos": (pos % 64).cast("int")})
    block = Window.partitionBy(FILE, "block_id")
    heads = {"n": F.count(F.lit(1)).over(block).cast("int")}
    for s in manifest.columns:
        x = F.col(s.name)
        heads |= {s.header("mn"): F.min(x).over(block), s.header("mx"): F.max(x).over(block), s.header("nulls"): F.max(x.isNull()).over(block)}
    rows = rows.withColumns(heads)
    values, aggs = {}, [F.first("n").alias("n"), F.bit_or(shl(lit(1), F.col("__pos"))).alias("live")]
    for s in manifest.columns:
        bias = {"block": F.coalesce(s.header("mn"), lit(0)), "file": F.coalesce(F.col(f"{s.name}__file_bias"), lit(0)) if s.bias == "file" else None}.get(s.bias, lit(s.base))
        values |= {f"__u_{s.name}": F.coalesce(F.col(s.name) - bias, lit(0)), s.header("bias"): bias}
        top = F.coalesce(F.col(s.header("mx")) - F.col(s.header("bias")), lit(0))
        bits = bit_width(F.first(top)) if s.width == "block" else F.lit(s.planes)
        aggs += [bits.cast("byte").alias(s.header("bits")), F.first(s.header("bias")).alias(s.header("bias")), F.first(s.header("mn")).alias(s.header("mn")), F.first(s.header("mx")).alias(s.header("mx"))]
        valid = F.bit_or(shl(F.col(s.name).isNotNull().cast("long"), F.col("__pos")))
        aggs.append(F.when(F.first(s.header("nulls")), valid).alias(s.header("v")))
        aggs += [F.bit_or(shl(F.shiftrightunsigned(F.col(f"__u_{s.name}"), j).bitwiseAND(lit(1)), F.col("__pos"))).alias(s.plane(j)) for j in range(s.planes)]
    return rows.withColumns(values).groupBy(FILE, "block_id", "word_no").agg(*aggs).select(*words_schema(manifest).fieldNames())


def blocks_schema(manifest: Manifest) -> StructType:
    fields = [StructField(FILE, LongType()), StructField("block_id", LongType()), StructField("n", IntegerType()), StructField("live", BinaryType())]
    for s in manifest.columns:
        fields += [StructField(s.header("bits"), ByteType()), *[StructField(s.header(h), LongType()) for h in ("bias", "mn", "mx")], StructField(s.header("v"), BinaryType()), StructField(s.header("planes"), BinaryType())]
    return StructType(fields)


def to_blocks(df: DataFrame, codecs: dict[str, Codec | tuple[Codec, Column]], manifest: Manifest) -> DataFrame:
    """One row a block: the block's own number of planes one after the other, N/8 bytes each."""
    schema = blocks_schema(manifest)
    step = manifest.block_size // 8

    def run(batches: Iterator[pa.RecordBatch]):
        for p in stretches(batches, manifest):
            n = len(p.block)
            live = p.live.reshape(n, step)
            cols = [pa.array(p.file), pa.array(p.block), pa.array(np.bitwise_count(live).sum(axis=1).astype(np.int32)), pa.array([x.tobytes() for x in live])]
            for s in manifest.columns:
                bits, bias, low, high, some, nulls, valid, planes, _ = p.columns[s.name]
                stack = np.stack([q.reshape(n, step) for q in planes], axis=1)
                cols += [pa.array(bits.astype(np.int8)), pa.array(bias.astype(np.int64)), *[pa.array(x, mask=~some) for x in (low, high)]]
                cols.append(pa.array([v.tobytes() if k else None for v, k in zip(valid.reshape(n, step), nulls)], pa.binary()))
                cols.append(pa.array([x[:b].tobytes() for x, b in zip(stack, bits)], pa.binary()))
            yield pa.RecordBatch.from_arrays(cols, schema.fieldNames())

    return with_ordinals(df, codecs, manifest).mapInArrow(run, schema)


def from_blocks(blocks: DataFrame, manifest: Manifest) -> DataFrame:
    """Back to rows: file_id, row_index and the ordinals; the check on ``to_blocks``."""
    size = manifest.block_size

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for r in batch.to_pylist():
                live = np.flatnonzero(np.unpackbits(np.frombuffer(r["live"], np.uint8), bitorder="little"))
                cols = [pa.array(np.full(len(live), r[FILE])), pa.array(r["block_id"] * size + live)]
                for s in manifest.columns:
                    raw = np.frombuffer(r[s.header("planes")], np.uint8).reshape(-1, size // 8)
                    x = np.zeros(size, np.uint64)
                    for j, p in enumerate(raw):
                        x |= np.unpackbits(p, bitorder="little").astype(np.uint64) << np.uint64(j)
                    x = (x + np.array(r[s.header("bias")]).astype(np.int64).view(np.uint64)).view(np.int64)[live]
                    v = r[s.header("v")]
                    gone = None if v is None else np.unpackbits(np.frombuffer(v, np.uint8), bitorder="little")[live] == 0
                    cols.append(pa.array(x, mask=gone))
                yield pa.RecordBatch.from_arrays(cols, [FILE, ROW, *[s.name for s in manifest.columns]])

    schema = f"{FILE} long, {ROW} long, " + ", ".join(f"{s.name} long" for s in manifest.columns)
    return blocks.mapInArrow(run, schema)
