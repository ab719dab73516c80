"""Streams: continuous encoding, windows, late data, a stateful block builder."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import encode
from ..operators.table import SlicedTable
from ..plans.spec import Manifest
from ..sources.sliced import read_sliced, record, scratch
from ..sources.tables import FILE, ROW


def stream(spark: SparkSession, path: str, per_batch: int = 1) -> DataFrame:
    """A Parquet file or folder as a stream."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") and not _is_dir(spark, path) else spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(path)


def _is_dir(spark: SparkSession, path: str) -> bool:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def run_to_table(df: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Runs all that is available now into Parquet and reads it back."""
    spark = df.sparkSession
    out, at = scratch(spark, label), scratch(spark, f"{label}-checkpoint")
    if mode == "append":
        df.writeStream.format("parquet").option("path", out).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(out)

    def last(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{batch_id:09d}")

    q = df.writeStream.outputMode(mode).option("checkpointLocation", at).trigger(availableNow=True).foreachBatch(last).start()
    q.awaitTermination()
    done = q.lastProgress
    return spark.read.schema(df.schema).parquet(f"{out}/{done['batchId']:09d}")


def ingest(events: DataFrame, codecs: dict, path: str, checkpoint: str, manifest: Manifest | None = None) -> None:
    """Encodes every micro-batch below ``path``; a repeated batch overwrites its own folder, so retries leave one copy.

    Every batch is a part with its own plane counts and bounds (block biases), so later values may be smaller,
    larger or null.  A ``manifest`` (encode.declare) saves the pass that finds the plane counts; values it cannot hold fail the batch.
    """

    def append(batch: DataFrame, batch_id: int) -> None:
        # Ids of one write: a partition's rows are numbered from 2**33 times its index on, which keeps its blocks apart.
        rows = batch.withColumn(FILE, F.lit(batch_id).cast("long")).withColumn(ROW, F.monotonically_increasing_id())
        m = manifest or encode.plan(rows, codecs, "block")
        record(encode.to_words(rows, codecs, m), m, path, f"batch-{batch_id}", lambda words: words.write.mode("overwrite").parquet(f"{path}/words/batch={batch_id}"))

    events.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(append).start().awaitTermination()


def ingested(spark: SparkSession, path: str) -> SlicedTable:
    return read_sliced(spark, path)


def timed(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width)).agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.col("window.start").alias("start"), "n", "cents")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return timed(events, delay).dropDuplicatesWithinWatermark(["event_id"])


def enrich(events: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream-static join."""
    return events.join(static, on, "left")


def late(events: DataFrame, delay: str = "1 hour", width: str = "1 hour") -> DataFrame:
    """Counts of windows that are closed by the watermark; rows that come after their window has been are left out."""
    return timed(events, delay).groupBy(F.window("ts", width)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


BLOCK = "shard long, block long, n long, lo long, bits int, planes array<array<long>>"


def pack_block(shard: int, block: int, xs: list[int]) -> dict:
    """A block's planes over its least value, 64 rows a word."""
    lo = min(xs)
    bits = max(1, (max(xs) - lo).bit_length())
    size = -(-len(xs) // 64) * 64
    dense = np.zeros(size, np.uint64)
    dense[: len(xs)] = [x - lo for x in xs]
    planes = [np.packbits((dense >> np.uint64(j) & np.uint64(1)).astype(np.uint8), bitorder="little").view(np.int64).tolist() for j in range(bits)]
    return {"shard": shard, "block": block, "n": len(xs), "lo": lo, "bits": bits, "planes": planes}


def block_builder(events: DataFrame, shard_col: str, value_col: str, block_size: int = 1024) -> DataFrame:
    """Packs a shard's rows into blocks as they come (the columns of BLOCK); null values are left out.

    A block goes out when it is full.  The tail goes out short at the end of every micro-batch in which its shard has rows, and again
    when it has grown, so no value waits for a timeout: of the rows of one (shard, block) the longest is the block (``finished``).
    """
    import pandas as pd

    def step(key, frames, state: GroupState):
        held, block = state.get if state.exists else ([], 0)
        held, out = list(held), []
        for f in frames:
            held += [int(x) for x in f[value_col]]
        while len(held) >= block_size:
            out.append(pack_block(key[0], block, held[:block_size]))
            held, block = held[block_size:], block + 1
        if held:
            out.append(pack_block(key[0], block, held))
        state.update((held, block))
        yield pd.DataFrame(out, columns=[c.split(" ")[0] for c in BLOCK.split(", ")])

    rows = events.where(F.col(value_col).isNotNull())
    return rows.groupBy(shard_col).applyInPandasWithState(step, BLOCK, "held array<long>, block long", "append", GroupStateTimeout.NoTimeout)


def finished(blocks: DataFrame) -> DataFrame:
    """The last state of every block."""
    return blocks.groupBy("shard", "block").agg(F.max_by(F.struct("n", "lo", "bits", "planes"), "n").alias("x")).select("shard", "block", "x.*")


def unpacked(blocks: DataFrame) -> DataFrame:
    """(shard, block, value) of packed blocks, in DataFrame functions."""
    at = blocks.withColumn("pos", F.explode(F.sequence(F.lit(0), F.col("n").cast("int") - 1)))
    word, bit = F.expr("cast(pos div 64 as int)"), (F.col("pos") % 64).cast("int")
    parts = F.transform("planes", lambda p, j: F.call_function("shiftleft", F.getbit(F.get(p, word), bit).cast("long"), j))
    return at.select("shard", "block", (F.col("lo") + F.aggregate(parts, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))).alias("value"))
