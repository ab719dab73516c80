"""Context-triggered piecewise hashing.

A rolling hash over seven bytes cuts a text where it hits the block size; each
piece gives one character, so a local edit changes a few characters of the
fingerprint.  The block size is 3 * 2**k, the smallest that gives at most 64
pieces on average, halved while fewer than 32 come out; a second signature at twice the size
lets neighbours in size be compared.  Likeness is one minus the insertion and
deletion distance over the two lengths, after a common run has been found.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

#: The fingerprint's digits, the rolling window and the lengths of the signatures.
DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
WINDOW, FULL, HALF, RUN = 7, 64, 32, 7


def levels(flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions behind which some block size cuts, and the largest such k of each."""
    x = flat.astype(np.uint32)
    total = np.zeros(len(x), np.uint32)
    shifted = np.zeros(len(x), np.uint32)
    for k in range(WINDOW):
        back = x[: len(x) - k]
        total[k:] += back * np.uint32(1 + WINDOW - k)
        shifted[k:] ^= back << np.uint32(5 * k)
    h = (total + shifted).astype(np.uint64) + np.uint64(1)
    at = np.flatnonzero(h % np.uint64(3) == 0)
    third = (h[at] // np.uint64(3)).astype(np.int64)
    low = third & -third
    return at, np.where(third == 0, 40, np.round(np.log2(np.maximum(low, 1)))).astype(np.int64)


def signature(raw: memoryview, cuts: np.ndarray, most: int) -> str:
    """One digit a piece; the last digit of a full signature covers the rest."""
    ends = (cuts + 1).tolist()
    if len(ends) >= most:
        ends = ends[: most - 1]
    if not ends or ends[-1] < len(raw):
        ends.append(len(raw))
    start, out = 0, []
    for end in ends:
        out.append(DIGITS[(zlib.crc32(raw[start:end]) * 0x9E3779B1 >> 20) & 63])
        start = end
    return "".join(out)


def fingerprints(texts: list[str]) -> list[str]:
    """``blocksize:signature:signature at twice the size``; the empty text gives ``3::``."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    gap = b"\0" * WINDOW
    flat = np.frombuffer(gap.join(raw) + gap, np.uint8)
    at, level = levels(flat)
    out, base = [], 0
    for r in raw:
        lo, hi = np.searchsorted(at, (base, base + len(r)))
        own, lev = at[lo:hi] - base, level[lo:hi]
        k = 0
        while 3 * (1 << k) * FULL < len(r):
            k += 1
        while k and int((lev >= k).sum()) < HALF:
            k -= 1
        view = memoryview(r)
        parts = [signature(view, own[lev >= j], most) if r else "" for j, most in ((k, FULL), (k + 1, HALF))]
        out.append(f"{3 << k}:{parts[0]}:{parts[1]}")
        base += len(r) + WINDOW
    return out


def common_length(a: str, b: str) -> int:
    """Longest common subsequence, one bit a position of ``a``."""
    at: dict[str, int] = {}
    for i, c in enumerate(a):
        at[c] = at.get(c, 0) | 1 << i
    full, v = (1 << len(a)) - 1, (1 << len(a)) - 1
    for c in b:
        u = v & at.get(c, 0)
        v = ((v + u) | (v - u)) & full
    return len(a) - v.bit_count()


def closeness(a: str, b: str) -> float:
    """0 without a common run of 7 digits (a third of a shorter signature), else 1 - distance / lengths."""
    if not a or not b:
        return float(a == b)
    run = min(RUN, max(1, min(len(a), len(b)) // 3))
    grams = {a[i : i + run] for i in range(len(a) - run + 1)}
    if not any(b[i : i + run] in grams for i in range(len(b) - run + 1)):
        return 0.0
    return 2 * common_length(a, b) / (len(a) + len(b))


def likeness(f: str, g: str) -> float:
    """0 to 1; block sizes more than a factor of two apart give 0, equal fingerprints 1."""
    if f == g:
        return 1.0
    (m, a1, a2), (n, b1, b2) = f.split(":"), g.split(":")
    if m == n:
        return max(closeness(a1, b1), closeness(a2, b2))
    if int(m) == 2 * int(n):
        return closeness(a1, b2)
    if 2 * int(m) == int(n):
        return closeness(a2, b1)
    return 0.0


def edited(text: str, after: str) -> str:
    k = len(text) // 3
    return text[: len(text) - k] + after[:k] if k else text


def fingerprint(df: DataFrame, text_col: str = "text", out_col: str = "fingerprint") -> DataFrame:
    """Adds each text's fingerprint; null counts as empty."""

    @F.pandas_udf("string")
    def run(texts):
        return texts.__class__(fingerprints([t or "" for t in texts]), index=texts.index, dtype=object)

    return df.withColumn(out_col, run(F.col(text_col)))


FIELDS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
NAMES = [f.split(" ")[0] for f in FIELDS.split(", ")]
KINDS = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]


def judged(ids: list, texts: list[str], after: list[str], prints: list[str], after_prints: list[str]) -> list[list]:
    changed = [edited(t, n) for t, n in zip(texts, after)]
    marks = fingerprints(changed)
    shas = [hashlib.sha256(c.encode("utf-8", "surrogatepass")).hexdigest() for c in changed]
    return [ids, [len(t) for t in texts], shas, prints, marks, [round(likeness(a, b), 6) for a, b in zip(prints, marks)], [round(likeness(a, b), 6) for a, b in zip(prints, after_prints)]]


def neighbours(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every document against its edited text and against the next one in descending id order.

    Texts are dealt by ranges of ids; only the first and last document of a range
    meet in a second, small step.  Null texts count as empty; null ids come last, rows that repeat an
    id are ordered by text.  A lone document is its own next one.
    """

    def run(batches: Iterator[pa.RecordBatch]):
        part, last, first = TaskContext.get().partitionId(), None, True
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                piece = batch.slice(i, 256)
                ids, texts = piece.column(0).to_pylist(), [t or "" for t in piece.column(1).to_pylist()]
                prints = fingerprints(texts)
                if first:
                    yield record(part, 2, [[ids[0]], [0], [None], [prints[0]], [None], [None], [None]], [texts[0]])
                    first = False
                if last is not None:
                    ids, texts, prints = [last[0], *ids], [last[1], *texts], [last[2], *prints]
                last = (ids[-1], texts[-1], prints[-1])
                if len(ids) > 1:
                    yield record(part, 0, judged(ids[:-1], texts[:-1], texts[1:], prints[:-1], prints[1:]), [None] * (len(ids) - 1))
        if last is not None:
            yield record(part, 1, [[last[0]], [0], [None], [last[2]], [None], [None], [None]], [last[1]])

    def record(part: int, kind: int, cols: list[list], texts: list) -> pa.RecordBatch:
        n = len(texts)
        head = [pa.array([part] * n, pa.int32()), pa.array([kind] * n, pa.int32())]
        return pa.RecordBatch.from_arrays([*head, *[pa.array(c, k) for c, k in zip(cols, KINDS)], pa.array(texts, pa.string())], ["part", "kind", *NAMES, "text"])

    def border(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            ids, texts, prints, after, after_prints = (c.to_pylist() for c in batch.columns)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(judged(ids, texts, after, prints, after_prints), KINDS)], NAMES)

    rows = df.select(F.col(id_col).cast("long").alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("__text"))
    order = F.col("__id").desc_nulls_last()
    dealt = rows.repartitionByRange(order).sortWithinPartitions(order, "__text")
    made = stored(dealt.mapInArrow(run, f"part int, kind int, {FIELDS}, text string"), "fingerprints")
    firsts = made.where("kind = 2").select("part", F.col("text").alias("after"), F.col("fingerprint").alias("after_print"))
    turn = Window.orderBy("part")  # a row a partition
    follows = made.where("kind = 2").select("part").withColumn("next", F.coalesce(F.lead("part").over(turn), F.first("part").over(turn)))
    lasts = made.where("kind = 1").join(follows, "part").join(firsts.withColumnRenamed("part", "next"), "next")
    patched = lasts.select("doc_id", "text", "fingerprint", "after", "after_print").mapInArrow(border, FIELDS)
    return made.where("kind = 0").select(*NAMES).unionByName(patched).withColumnRenamed("doc_id", id_col)
