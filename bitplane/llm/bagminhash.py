"""Weighted MinHash signatures from hierarchical Poisson processes.

A document is the multiset of its five-word shingles.  The weight axis of every
shingle is cut into unit levels, and dyadic stretches of it ([0,1), [1,2), [2,4),
...) each own a Poisson process whose points carry an arrival time, a register and
a level found by halving the stretch.  A shingle of weight w sees the points below
level w, the same points in every document, so that the earliest point of a
register is shared by two documents with the probability of their weighted
Jaccard similarity.  Points are made in order of arrival and a process stops as
soon as it is later than all registers of its document, so a shingle costs a few
points instead of one a register.
"""

from __future__ import annotations

import re

import numpy as np
import xxhash

U = np.uint64
GOLDEN, MIX1, MIX2 = U(0x9E3779B97F4A7C15), U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)
WORDS = re.compile(r"\w+").findall


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer."""
    x = (x ^ (x >> U(30))) * MIX1
    x = (x ^ (x >> U(27))) * MIX2
    return x ^ (x >> U(31))


class WordHashes(dict):
    #: Larger memos are no faster here and stay in memory as long as the worker lives.
    LIMIT = 100_000

    def __missing__(self, word: str) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h


HASHES = WordHashes()


def shingles(texts: list[str], width: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles of each text: owner, hash, weight; and the words of each text.

    Words are runs of letters, digits and underscores in lower case.  A text of fewer than
    ``width`` words is one shingle; a text without words has none.
    """
    lists = [WORDS(t.lower()) for t in texts]
    n_words = np.fromiter(map(len, lists), np.int64, len(lists))
    padded = np.where((n_words > 0) & (n_words < width), width, n_words)
    hashes = np.zeros(int(padded.sum()), U)
    begin = np.cumsum(padded) - padded
    for at, words in zip(begin.tolist(), lists):
        hashes[at : at + len(words)] = np.fromiter(map(HASHES.__getitem__, words), U, len(words))
    owner = np.repeat(np.arange(len(texts)), padded)
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, np.int64), np.empty(0, U), np.empty(0, np.int64), n_words
    rolled = hashes[:n].copy()
    for i in range(1, width):
        rolled = rolled * MIX1 + hashes[i : i + n]
    own = owner[:n] == owner[width - 1 :]
    owner, rolled = owner[:n][own], mix(rolled[own])
    order = np.lexsort((rolled, owner))
    owner, rolled = owner[order], rolled[order]
    first = np.flatnonzero(np.r_[True, (owner[1:] != owner[:-1]) | (rolled[1:] != rolled[:-1])])
    return owner[first], rolled[first], np.diff(np.r_[first, len(rolled)]), n_words


def occurrences(owner: np.ndarray, hashes: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The multisets as sets: the k-th occurrence of a shingle is an element of its own."""
    rep = np.repeat(np.arange(len(hashes)), weights)
    k = np.arange(len(rep)) - np.repeat(np.cumsum(weights) - weights, weights)
    return owner[rep], np.where(k == 0, hashes[rep], mix(hashes[rep] + k.astype(U) * GOLDEN))


def signatures(n_docs: int, owner: np.ndarray, hashes: np.ndarray, weights: np.ndarray, registers: int) -> np.ndarray:
    """One row of registers a document; infinite where a document has no shingle."""
    out = np.full(n_docs * registers, np.inf)
    depth = np.ceil(np.log2(np.maximum(weights, 1))).astype(np.int64) + 1  # stretches that begin below the weight
    rep = np.repeat(np.arange(len(hashes)), depth)
    node = np.arange(len(rep)) - np.repeat(np.cumsum(depth) - depth, depth)
    low = np.where(node == 0, 0, 1 << np.maximum(node - 1, 0))
    size = np.where(node == 0, 1, low)
    doc, weight, key = owner[rep], weights[rep], mix(hashes[rep] ^ (node.astype(U) * MIX2))
    rate = 1.0 / (size * float(registers))
    time = np.zeros(len(rep))
    while len(doc):
        key = mix(key + GOLDEN)
        time = time - np.log1p(-(key >> U(11)).astype(np.float64) * 2.0**-53) * rate
        place = mix(key ^ MIX1)
        slot = doc * registers + (place % U(registers)).astype(np.int64)
        level = low + ((place >> U(32)) & (size - 1).astype(U)).astype(np.int64)
        real = level < weight
        np.minimum.at(out, slot[real], time[real])
        docs, back = np.unique(doc, return_inverse=True)
        latest = out.reshape(n_docs, registers)[docs].max(axis=1)
        going = time < latest[back]
        doc, weight, key, rate, time, low, size = (x[going] for x in (doc, weight, key, rate, time, low, size))
    return out.reshape(n_docs, registers)


def bands(signature: np.ndarray, rows: int) -> np.ndarray:
    """Bucket hashes, one column a band of ``rows`` registers."""
    bits = signature.view(U)
    cols = []
    for b in range(signature.shape[1] // rows):
        h = np.full(len(bits), U(b + 1)) * GOLDEN
        for i in range(rows):
            h = mix(h ^ bits[:, b * rows + i]) + GOLDEN
        cols.append(h)
    return np.stack(cols, axis=1).view(np.int64)
