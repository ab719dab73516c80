"""Encoded datasets on disk: Parquet words and a manifest with one JSON entry for each part written."""

from __future__ import annotations

import dataclasses
import json
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..operators.encode import words_schema
from ..operators.table import SlicedTable
from ..plans.spec import Manifest
from .tables import FILE


def write_sliced(table: SlicedTable, path: str, mode: str = "error", sort: bool = False) -> None:
    """One sliced file for each task of the source.  ``sort`` restores file order after a shuffle.

    Appended words may lie outside the dataset's bounds, hold nulls and need more planes; codecs, biases and
    block size must agree (encode.plan with ``like``), which is checked before anything is written.
    """
    spark = table.words.sparkSession
    if mode == "append":
        Manifest.merged([*_parts(spark, path).values(), table.manifest])
    words = table.words.sortWithinPartitions(FILE, "block_id", "word_no") if sort else table.words
    record(words, table.manifest, path, uuid.uuid4().hex, lambda seen: seen.write.mode(mode).parquet(f"{path}/words"), mode)


def record(words: DataFrame, manifest: Manifest, path: str, part: str, write: Callable[[DataFrame], None], mode: str = "append") -> Manifest:
    """Writes words and their part of the manifest, with the bounds seen while writing.

    The part is first entered as open, which keeps readers from trusting any bound until its bounds are known.
    """
    spark = words.sparkSession

    def enter(m: Manifest, how: str) -> None:
        text = json.dumps({"part": part, "manifest": m.to_json()})
        spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode(how).text(f"{path}/manifest")

    enter(manifest.open(), mode)
    seen = Observation()
    bounds = [f for s in manifest.columns for f in (F.min(s.header("mn")).alias(f"{s.name}__lo"), F.max(s.header("mx")).alias(f"{s.name}__hi"), F.max(F.col(s.header("v")).isNotNull()).alias(f"{s.name}__nulls"))]
    write(words.observe(seen, F.coalesce(F.sum(F.bit_count("live").cast("long")), F.lit(0)).alias("rows"), *bounds))
    got = seen.get
    cols = [dataclasses.replace(s, lo=got[f"{s.name}__lo"], hi=got[f"{s.name}__hi"], has_nulls=bool(got[f"{s.name}__nulls"])) for s in manifest.columns]
    exact = dataclasses.replace(manifest, columns=tuple(cols), rows=got["rows"], exact=True)
    enter(exact, "append")
    return exact


def _parts(spark: SparkSession, path: str) -> dict[str, Manifest]:
    """Each part's manifest: the closed entry if there is one, else the open one."""
    out: dict[str, Manifest] = {}
    for row in spark.read.text(f"{path}/manifest").collect():  # two rows a write
        entry = json.loads(row[0])
        m = Manifest.from_json(entry["manifest"])
        if m.exact or entry["part"] not in out:
            out[entry["part"]] = m
    return dict(sorted(out.items()))


def read_manifest(spark: SparkSession, path: str) -> Manifest:
    return Manifest.merged(list(_parts(spark, path).values()))


def read_words(spark: SparkSession, path: str, parts: list[Manifest]) -> DataFrame:
    """Words of all parts; planes that a part did not need read as empty."""
    whole = Manifest.merged(parts)
    schema = words_schema(whole)
    words = spark.read.schema(schema).parquet(path).select(*schema.fieldNames())
    missing = [s.plane(j) for i, s in enumerate(whole.columns) for j in range(min(p.columns[i].planes for p in parts), s.planes)]
    return words.withColumns({c: F.coalesce(c, F.lit(0).cast("long")) for c in missing}) if missing else words


def read_sliced(spark: SparkSession, path: str, base: DataFrame | None = None) -> SlicedTable:
    parts = list(_parts(spark, path).values())
    return SlicedTable(read_words(spark, f"{path}/words", parts), Manifest.merged(parts), base)


def compact(spark: SparkSession, path: str, out: str, files: int) -> None:
    """Rewrites many small word files as ``files`` ordered ones, under one manifest."""
    table = read_sliced(spark, path)
    words = table.words.repartitionByRange(files, FILE, "block_id").sortWithinPartitions(FILE, "block_id", "word_no")
    write_sliced(SlicedTable(words, table.manifest), out)


def scratch(spark: SparkSession, label: str) -> str:
    from ..session import shared_dir

    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def stored_bytes(words: DataFrame) -> DataFrame:
    """Bytes of the data files behind a table, by file."""
    return words.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_size").alias("bytes")).distinct()
