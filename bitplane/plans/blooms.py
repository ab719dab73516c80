"""Bloom filters in word headers: 512 bits for 64 values, in eight BIGINT columns.

A value's hash picks one of the eight columns and four bits in it, so a constant is tested on one
column of one word, and the other seven are never read for it.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.bits import lit
from .spec import ColumnSpec

PARTS, HASHES = 8, 4
U64 = (1 << 64) - 1
#: Multipliers of a 64-bit finalizer.
FIRST, SECOND = 0xBF58476D1CE4E5B9, 0x94D049BB133111EB


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ x >> np.uint64(30)
    x = x * np.uint64(FIRST)
    x = (x ^ x >> np.uint64(27)) * np.uint64(SECOND)
    return x ^ x >> np.uint64(31)


def places(ordinals: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The column and the bits in it of each ordinal."""
    h = mix(ordinals.astype(np.int64).view(np.uint64))
    bits = np.zeros(len(h), np.uint64)
    for i in range(HASHES):
        bits |= np.uint64(1) << (h >> np.uint64(8 + 6 * i) & np.uint64(63))
    return (h & np.uint64(PARTS - 1)).astype(np.int64), bits


def names(spec: ColumnSpec) -> list[str]:
    return [spec.header(f"f{i}") for i in range(PARTS)] if spec.bloom else []


def build(ordinals: np.ndarray, words: np.ndarray, n_words: int) -> list[np.ndarray]:
    part, bits = places(ordinals)
    out = np.zeros((PARTS, n_words), np.uint64)
    np.bitwise_or.at(out, (part, words), bits)
    return [x.view(np.int64) for x in out]


def may_hold(spec: ColumnSpec, ordinal: int) -> Column:
    part, bits = places(np.array([ordinal], np.int64))
    need = int(bits.view(np.int64)[0])
    return F.col(names(spec)[int(part[0])]).bitwiseAND(lit(need)) == lit(need)
