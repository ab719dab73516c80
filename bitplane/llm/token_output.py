"""Token ids in Arrow's file format: batches of fixed-size lists, read without copies.

A range of document ids becomes one file of equal-length sequences (``ids`` and
``mask``; only the last sequence of a file is padded) and one index file with
the documents' places.  Ids take the narrowest unsigned type that holds the
vocabulary, masks a bit each.  File names carry a random part and are published by the
manifest that Spark commits, so retried or speculative tasks leave no trace in it.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tokenizing import encoder, portions

MANIFEST = "part int, file string, index string, documents long, tokens long, sequences long, batch_rows int, seq_len int"

INDEX = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


class SequenceWriter:
    """Packs a stream of ids into fixed-size-list batches; holds one batch at most."""

    def __init__(self, sink, seq_len: int, rows: int, largest_id: int):
        self.seq_len, self.rows = seq_len, rows
        kind = np.uint16 if largest_id < 1 << 16 else np.uint32
        self.buffer, self.filled = np.zeros(seq_len * rows, kind), 0
        self.schema = pa.schema([("ids", pa.list_(pa.from_numpy_dtype(kind), seq_len)), ("mask", pa.list_(pa.bool_(), seq_len))])
        self.out = pa.ipc.new_file(sink, self.schema)
        self.tokens = self.sequences = 0

    def push(self, ids: np.ndarray) -> None:
        self.tokens += len(ids)
        while len(ids):
            n = min(len(ids), len(self.buffer) - self.filled)
            self.buffer[self.filled : self.filled + n] = ids[:n]
            self.filled, ids = self.filled + n, ids[n:]
            if self.filled == len(self.buffer):
                self.flush()

    def flush(self) -> None:
        rows = -(-self.filled // self.seq_len)
        if not rows:
            return
        size = rows * self.seq_len
        self.buffer[self.filled : size] = 0
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), self.seq_len) for x in (self.buffer[:size], np.arange(size) < self.filled)]
        self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))
        self.sequences, self.filled = self.sequences + rows, 0

    def close(self) -> None:
        self.flush()
        self.out.close()


class SequenceReader:
    """Random access to tokens and sequences of one file; slices point into the mapped file."""

    def __init__(self, source, seq_len: int, rows: int):
        self.file = pa.ipc.open_file(source)
        self.seq_len, self.span = seq_len, seq_len * rows
        self.at, self.values = -1, None

    def batch(self, k: int) -> np.ndarray:
        if k != self.at:
            self.at, self.values = k, self.file.get_batch(k).column(0).values.to_numpy(zero_copy_only=True)
        return self.values

    def pieces(self, start: int, n: int):
        while n > 0:
            k, off = divmod(start, self.span)
            piece = self.batch(k)[off : off + n]
            yield piece
            start, n = start + len(piece), n - len(piece)

    def sequence(self, row: int) -> np.ndarray:
        return next(self.pieces(row * self.seq_len, self.seq_len))


def open_source(path: str):
    fs, name = pafs.FileSystem.from_uri(path)
    return pa.memory_map(name) if isinstance(fs, pafs.LocalFileSystem) else fs.open_input_file(name)


def write_sequences(df: DataFrame, path: str, vocabulary: str, seq_len: int = 2048, batch_rows: int = 128, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Writes all documents in ascending id order below ``path``; returns the manifest's place.

    Null texts are empty (their end id alone).  Rows without id come first; rows
    that repeat an id stay apart, ordered by text.  An empty table writes an empty manifest.
    """

    def run(batches):
        fs, root = pafs.FileSystem.from_uri(path)
        fs.create_dir(root)
        enc, part = encoder(vocabulary), TaskContext.get().partitionId()
        name = f"part-{part:06d}-{uuid.uuid4().hex}"
        sinks, writer, index, docs = [], None, None, 0
        for rows, texts in portions(batches):
            if writer is None:
                sinks = [fs.open_output_stream(f"{root}/{name}.{kind}") for kind in ("arrow", "index")]
                writer = SequenceWriter(sinks[0], seq_len, batch_rows, max(end_id, *enc.rules.names))
                index = pa.ipc.new_file(sinks[1], INDEX)
            starts, sizes = [], []
            for portions_of_text in enc.encode_many(texts):
                starts.append(writer.tokens)
                for ids in portions_of_text:
                    writer.push(ids)
                writer.push(np.array([end_id]))
                sizes.append(writer.tokens - starts[-1])
            docs += len(texts)
            index.write_batch(pa.RecordBatch.from_arrays([rows.column(0), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64())], schema=INDEX))
        if writer is not None:
            writer.close()
            index.close()
            for s in sinks:
                s.close()
            row = [[part], [f"{name}.arrow"], [f"{name}.index"], [docs], [writer.tokens], [writer.sequences], [batch_rows], [seq_len]]
            kinds = [pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(row, kinds)], ["part", "file", "index", "documents", "tokens", "sequences", "batch_rows", "seq_len"])

    rows = df.select(F.col(id_col).cast("long").alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("__text"))
    ordered = rows.repartitionByRange(F.col("__id").asc_nulls_first()).sortWithinPartitions(F.col("__id").asc_nulls_first(), "__text")
    manifest = f"{path}/manifest"
    ordered.mapInArrow(run, MANIFEST).write.parquet(manifest)
    return manifest


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the files: doc_id, start (over all files), n_tokens, ids_crc32."""
    files = spark.read.schema(MANIFEST).parquet(f"{path}/manifest")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    placed = files.withColumn("offset", F.coalesce(F.sum("tokens").over(before), F.lit(0)))

    def run(batches):
        for batch in batches:
            for f in batch.to_pylist():
                reader = SequenceReader(open_source(f"{path}/{f['file']}"), f["seq_len"], f["batch_rows"])
                index = pa.ipc.open_file(open_source(f"{path}/{f['index']}"))
                for k in range(index.num_record_batches):
                    ids, starts, sizes = index.get_batch(k).columns
                    sums = []
                    for start, n in zip(starts.to_pylist(), sizes.to_pylist()):
                        crc = 0
                        for piece in reader.pieces(start, n):
                            crc = zlib.crc32(piece.astype("<u4"), crc)
                        sums.append(crc)
                    yield pa.RecordBatch.from_arrays([ids, pa.array(starts.to_numpy() + f["offset"]), sizes, pa.array(sums, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    spread = max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    return placed.repartition(spread, "part").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
