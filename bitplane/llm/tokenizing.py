"""Tokenizer operators over DataFrames: counts, and encode-decode round trips."""

from __future__ import annotations

import contextlib
import functools
import gc
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import MergeList, TokenDecoder, WordEncoder
from .common import lean
from .token_counts import TokenCounter

#: Rows handled at once; memory is bounded by them and by the longest text.
ROWS = 512


@functools.lru_cache(maxsize=2)
def encoder(path: str) -> WordEncoder:
    """One encoder a worker process, so that its memo outlives the task, unless ``memo_for_task`` ends it."""
    gc.disable()  # the memo holds no cycles, and scanning it costs more than the work
    return WordEncoder(MergeList.load(path))


@functools.lru_cache(maxsize=2)
def decoder(path: str) -> TokenDecoder:
    return TokenDecoder(encoder(path).rules)


@functools.lru_cache(maxsize=2)
def counter(path: str) -> TokenCounter:
    gc.disable()
    return TokenCounter(MergeList.load(path))


@contextlib.contextmanager
def memo_for_task(enc: WordEncoder) -> Iterator[None]:
    """Empties the memo when a task ends: the worker process goes on to run other operators' tasks."""
    gc.disable()
    try:
        yield
    finally:
        enc.memo.clear()
        gc.enable()


def portions(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    for batch in batches:
        for i in range(0, batch.num_rows, ROWS):
            part = batch.slice(i, ROWS)
            yield part, [t or "" for t in part.column(1).to_pylist()]


def count_tokens(df: DataFrame, vocabulary: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, n_bytes, n_tokens, over_limit.  Null counts as empty: no bytes, no tokens."""

    def run(batches):
        counts = counter(vocabulary)
        for part, texts in portions(batches):
            counts.learn(texts)
            tokens = np.fromiter(map(counts.count, texts), np.int64, len(texts))
            sizes = np.fromiter((len(t.encode("utf-8", "surrogatepass")) for t in texts), np.int64, len(texts))
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes), pa.array(tokens), pa.array(tokens > limit)], ["__id", "n_bytes", "n_tokens", "over_limit"])

    rows = df.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__text"))
    return rows.mapInArrow(run, "__id long, n_bytes long, n_tokens long, over_limit boolean").withColumnRenamed("__id", id_col)


def encode(df: DataFrame, vocabulary: str, text_col: str = "text", out_col: str = "token_ids") -> DataFrame:
    """All columns of ``df`` and the ids of each text (empty for null and empty texts).

    A column of the same name as ``out_col`` is replaced.
    """
    kept = [c for c in df.columns if c != out_col]

    @F.pandas_udf("array<int>")
    def ids_of(texts):
        enc, out = encoder(vocabulary), []
        whole = [t or "" for t in texts]
        for ids in enc.encode_many(whole):
            out.append(np.concatenate([np.empty(0, np.int32), *ids]).astype(np.int32))
        return texts.__class__(out, index=texts.index)

    return df.select(*[F.col(f"`{c}`") for c in kept], ids_of(F.col(text_col)).alias(out_col))


def decode(df: DataFrame, vocabulary: str, ids_col: str = "token_ids", out_col: str = "decoded", surface: bool = False) -> DataFrame:
    """Adds the text of each id list; ``surface`` joins token strings by spaces instead.  Null ids give null."""

    @F.pandas_udf("string")
    def text_of(lists):
        dec = TokenDecoder(encoder(vocabulary).rules, surface)
        return lists.map(lambda ids: None if ids is None else dec.push(ids) + dec.finish())

    return df.withColumn(out_col, text_of(F.col(ids_col)))


def round_trip(df: DataFrame, vocabulary: str, keep_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, n_tokens, ids_sha256, decoded_sha256 of the streamed ids and of the streamed decoding.

    ``keep_ids`` adds the ids themselves (token_ids).  Null counts as empty: no ids.
    """

    def run(batches):
        enc, dec = encoder(vocabulary), decoder(vocabulary)
        with memo_for_task(enc):
            for part, texts in portions(batches):
                counts, ids_sha, text_sha, lists = [], [], [], []
                for portions_of_text in enc.encode_many(texts):
                    n, ids_hash, text_hash, kept = 0, hashlib.sha256(), hashlib.sha256(), []
                    for ids in portions_of_text:
                        n += len(ids)
                        ids_hash.update(ids)
                        if keep_ids:
                            kept.append(ids)
                        text_hash.update(dec.push(ids).encode())
                    text_hash.update(dec.finish().encode())
                    counts.append(n)
                    ids_sha.append(ids_hash.hexdigest())
                    text_sha.append(text_hash.hexdigest())
                    if keep_ids:
                        lists.append(np.concatenate([np.empty(0, np.int32), *kept]).astype(np.int32))
                cols = [part.column(0), pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())]
                if keep_ids:
                    cols.append(pa.array(lists, pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, names)

    schema = "__id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", token_ids array<int>" * keep_ids
    names = [f.split(" ")[0] for f in schema.split(", ")]
    rows = df.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__text"))
    return rows.mapInArrow(lean(run), schema).withColumnRenamed("__id", id_col)
