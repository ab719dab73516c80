"""Three engines for bound predicates: generated code, numpy over Arrow, and array functions.

All walk the planes from the lowest bit up with a single running mask: for x > c
the mask keeps rows whose lower bits decide for them, a plane is OR-ed in where
the constant's bit is 0 and AND-ed where it is 1.  The start value decides between > (none) and
>= (all).  An expression therefore grows by one operation a plane.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.bits import all_of, any_of, lit, positions, shl
from .spec import ColumnSpec, Manifest

U64 = (1 << 64) - 1


def signed(x: int) -> int:
    x &= U64
    return x - (1 << 64) if x >> 63 else x


def validity(spec: ColumnSpec, live: Column) -> Column:
    """The validity word; a missing one means that no value is null."""
    return F.coalesce(F.col(spec.header("v")), lit(-1)).bitwiseAND(live) if spec.has_nulls else live


# --- generated code


def catalyst(node: tuple, manifest: Manifest, mode: str = "skip") -> Column:
    """The mask of a word.  ``skip`` decides words by their block's extremes where it can; ``oblivious`` always reads all planes."""
    live = F.col("live")
    if node[0] in ("and", "or"):
        parts = [catalyst(x, manifest, mode) for x in node[1]]
        return all_of(parts) if node[0] == "and" else any_of(parts)
    if node[0] == "none":
        return lit(0)
    if node[0] == "valid":
        return validity(manifest[node[1]], live)
    if node[0] == "null":
        return live.bitwiseAND(F.bitwise_not(validity(manifest[node[1]], live)))
    if node[0] == "cols":
        a, b = manifest[node[2]], manifest[node[3]]
        return _columns(node[1], a, b).bitwiseAND(validity(a, live)).bitwiseAND(validity(b, live))
    if node[0] == "set":
        spec = manifest[node[1]]
        found = _members(spec, node[2], mode)
        return (F.bitwise_not(found) if node[3] else found).bitwiseAND(validity(spec, live))
    _, name, op, k = node
    spec = manifest[name]
    # One text a leaf: building it out of column objects would cost a call into the JVM for every plane.
    valid = f"(coalesce({quoted(spec.header('v'))}, -1L) & live)" if spec.has_nulls else "live"
    return F.expr(f"({_leaf(spec, op, k, mode)} & {valid})")


def quoted(name: str) -> str:
    return f"`{name.replace('`', '``')}`"


def number(k: int) -> str:
    return f"({k}L)" if k > -(1 << 63) else "(-9223372036854775807L - 1L)"


def _members(spec: ColumnSpec, codes: tuple[int, ...], mode: str) -> Column:
    """Rows whose value is in a hash set: values are put together from the planes, word by word, where the extremes allow a hit."""
    def value(pos: Column) -> Column:
        bits = any_of([F.shiftleft(F.getbit(F.col(spec.plane(j)), pos).cast("long"), j) for j in range(spec.planes)])
        return bits if spec.literal else bits + F.col(spec.header("bias"))

    wanted = [signed(k - spec.base) if spec.literal else k for k in codes]
    at = F.filter(positions(F.col("live")), lambda pos: value(pos).isin(wanted))
    found = F.aggregate(at, lit(0), lambda m, pos: m.bitwiseOR(shl(lit(1), pos)))
    if mode != "skip":
        return found
    return F.when((F.col(spec.header("mx")) < codes[0]) | (F.col(spec.header("mn")) > codes[-1]), lit(0)).otherwise(found)


def _leaf(spec: ColumnSpec, op: str, k: int, mode: str) -> str:
    """SQL of a comparison's mask."""
    planes = [quoted(spec.plane(j)) for j in range(spec.planes)]
    if spec.literal:
        c = k - spec.base
        if c < 0 or c >> spec.planes:
            return "(-1L)" if (op in ("gt", "ge", "ne")) == (c < 0) or op == "ne" else "0L"
        out = _literal(op, planes, c)
        if mode != "skip":
            return out
    else:
        # Blocks that the extremes decide are not computed, so the difference below cannot overflow.
        out = _per_block(op, planes, f"({number(k)} - {quoted(spec.header('bias'))})")
    mn, mx, k = quoted(spec.header("mn")), quoted(spec.header("mx")), number(k)
    every, none = {
        "gt": (f"{mn} > {k}", f"{mx} <= {k}"), "ge": (f"{mn} >= {k}", f"{mx} < {k}"), "lt": (f"{mx} < {k}", f"{mn} >= {k}"), "le": (f"{mx} <= {k}", f"{mn} > {k}"),
        "eq": (f"{mn} = {k} AND {mx} = {k}", f"{mn} > {k} OR {mx} < {k}"), "ne": (f"{mn} > {k} OR {mx} < {k}", f"{mn} = {k} AND {mx} = {k}"),
    }[op]
    if mode == "skip":
        return f"CASE WHEN {every} THEN -1L WHEN {none} THEN 0L ELSE {out} END"
    return f"CASE WHEN {mn} <= {k} AND {mx} >= {k} THEN {out} WHEN {every} THEN -1L ELSE 0L END"


def _literal(op: str, planes: list[str], c: int) -> str:
    if op in ("eq", "ne"):
        same = " & ".join(p if c >> j & 1 else f"~{p}" for j, p in enumerate(planes))
        return f"({same})" if op == "eq" else f"~({same})"
    g = "-1L" if op in ("ge", "lt") else "0L"
    for j, p in enumerate(planes):
        g = f"({p} {'&' if c >> j & 1 else '|'} {g})"
    return f"~{g}" if op in ("lt", "le") else g


def _per_block(op: str, planes: list[str], delta: str) -> str:
    """As above with the constant's bits spread to whole words: -1 where set, 0 where not."""
    ones = [f"(-(shiftrightunsigned({delta}, {j}) & 1L))" for j in range(len(planes))]
    if op in ("eq", "ne"):
        differ = " | ".join(f"({p} ^ {m})" for p, m in zip(planes, ones))
        return f"~({differ})" if op == "eq" else f"({differ})"
    g = "-1L" if op in ("ge", "lt") else "0L"
    for p, m in zip(planes, ones):
        g = f"(({p} & ~{m}) | ({g} & ({p} ^ ~{m})))"
    return f"~{g}" if op in ("lt", "le") else g


def _columns(op: str, a: ColumnSpec, b: ColumnSpec) -> Column:
    """a op b plane by plane; the narrower column is padded with empty planes.  Needs equal bases."""
    if a.base != b.base:
        raise ValueError("encode both columns with one base to compare them")
    n = max(a.planes, b.planes)
    pa = [F.col(a.plane(j)) if j < a.planes else lit(0) for j in range(n)]
    pb = [F.col(b.plane(j)) if j < b.planes else lit(0) for j in range(n)]
    if op in ("eq", "ne"):
        differ = any_of([x.bitwiseXOR(y) for x, y in zip(pa, pb)])
        return differ if op == "ne" else F.bitwise_not(differ)
    g = lit(-1 if op in ("ge", "lt") else 0)
    for x, y in zip(pa, pb):
        g = x.bitwiseAND(F.bitwise_not(y)).bitwiseOR(g.bitwiseAND(F.bitwise_not(x.bitwiseXOR(y))))
    return F.bitwise_not(g) if op in ("lt", "le") else g


# --- numpy


def numpy_mask(node: tuple, manifest: Manifest, column, kernel: str = "lsb", lane_bits: int = 64) -> np.ndarray:
    """The masks of a batch.  ``column(name)`` gives an int64 array (None where a validity word is missing).

    ``msb_two_mask`` is the ablation with two running masks from the highest bit
    down; ``lane_bits`` runs the same operations over narrower registers.
    """
    lane = {64: np.uint64, 32: np.uint32, 16: np.uint16, 8: np.uint8}[lane_bits]
    live = column("live")

    def valid(spec: ColumnSpec) -> np.ndarray:
        v = column(spec.header("v")) if spec.has_nulls else None
        return live if v is None else v & live

    def walk(x: tuple) -> np.ndarray:
        if x[0] in ("and", "or"):
            return (np.bitwise_and if x[0] == "and" else np.bitwise_or).reduce([walk(y) for y in x[1]])
        if x[0] == "none":
            return np.zeros_like(live)
        if x[0] == "valid":
            return valid(manifest[x[1]])
        if x[0] == "null":
            return live & ~valid(manifest[x[1]])
        if x[0] == "cols":
            raise ValueError("the numpy engine compares columns with constants only")
        if x[0] == "set":
            spec = manifest[x[1]]
            value = np.zeros(len(live) * 64, np.uint64)
            for j in range(spec.planes):
                value |= np.unpackbits(np.ascontiguousarray(column(spec.plane(j))).view(np.uint8), bitorder="little").astype(np.uint64) << np.uint64(j)
            base = np.full(len(live), spec.base & U64, np.uint64) if spec.literal else column(spec.header("bias")).view(np.uint64)
            hit = np.isin((value + np.repeat(base, 64)).view(np.int64), np.array(x[2], np.int64))
            mask = np.packbits(hit, bitorder="little").view(np.int64)
            return (~mask if x[3] else mask) & valid(spec)
        _, name, op, k = x
        spec = manifest[name]
        n = len(live)
        planes = [np.ascontiguousarray(column(spec.plane(j))).view(lane) for j in range(spec.planes)]
        if spec.literal:
            c = k - spec.base
            low, high, delta = np.full(n, c < 0), np.full(n, c >> spec.planes > 0), np.full(n, c & U64, np.uint64)
            uniform = None if c < 0 or c >> spec.planes else c
        else:
            mn, mx = column(spec.header("mn")), column(spec.header("mx"))
            low, high = k < mn, k > mx
            delta, uniform = np.full(n, k & U64, np.uint64) - column(spec.header("bias")).view(np.uint64), None
        per = 64 // lane_bits
        if uniform is not None:
            ones = [lane(0) - lane(uniform >> j & 1) if uniform >> j & 1 == 0 else np.array(-1).astype(lane) for j in range(spec.planes)]
        else:
            ones = [np.repeat((np.uint64(0) - (delta >> np.uint64(j) & np.uint64(1))).astype(lane), per) for j in range(spec.planes)]
        out = _numpy_cmp(op, planes, ones, kernel).view(np.int64)
        every, none = {"gt": (low, high), "ge": (low, high), "lt": (high, low), "le": (high, low), "eq": (None, low | high), "ne": (low | high, None)}[op]
        out = out if every is None else np.where(every, np.int64(-1), out)
        out = out if none is None else np.where(none, np.int64(0), out)
        return out & valid(spec)

    return walk(node)


def _numpy_cmp(op: str, planes: list[np.ndarray], ones: list, kernel: str) -> np.ndarray:
    if op in ("eq", "ne"):
        differ = np.zeros_like(planes[0])
        for p, m in zip(planes, ones):
            differ |= p ^ m
        return differ if op == "ne" else ~differ
    if kernel == "msb_two_mask":
        equal, above = ~np.zeros_like(planes[0]), np.zeros_like(planes[0])
        for p, m in zip(reversed(planes), reversed(ones)):
            above |= equal & p & ~m
            equal &= ~(p ^ m)
        g = above | equal if op in ("ge", "lt") else above
    else:
        g = ~np.zeros_like(planes[0]) if op in ("ge", "lt") else np.zeros_like(planes[0])
        for p, m in zip(planes, ones):
            g = p & ~m | g & (p ^ ~m)
    return ~g if op in ("lt", "le") else g


# --- array functions


def array_mask(node: tuple, manifest: Manifest) -> Column:
    """Cross-check over arrays of planes (literal biases only), without code generation."""
    live = F.col("live")
    if node[0] in ("and", "or"):
        parts = [array_mask(x, manifest) for x in node[1]]
        return all_of(parts) if node[0] == "and" else any_of(parts)
    if node[0] == "cols":
        raise ValueError("not in this engine")
    if node[0] != "cmp":
        return catalyst(node, manifest)
    _, name, op, k = node
    spec = manifest[name]
    c = k - spec.base
    if not spec.literal or c < 0 or c >> spec.planes:
        return catalyst(node, manifest)
    bits = F.array(*[lit(-(c >> j & 1)) for j in range(spec.planes)])
    pairs = F.arrays_zip(F.array(*[F.col(spec.plane(j)) for j in range(spec.planes)]).alias("p"), bits.alias("m"))
    if op in ("eq", "ne"):
        differ = F.aggregate(pairs, lit(0), lambda g, x: g.bitwiseOR(x["p"].bitwiseXOR(x["m"])))
        out = differ if op == "ne" else F.bitwise_not(differ)
    else:
        g = F.aggregate(pairs, lit(-1 if op in ("ge", "lt") else 0), lambda g, x: x["p"].bitwiseAND(F.bitwise_not(x["m"])).bitwiseOR(g.bitwiseAND(x["p"].bitwiseXOR(F.bitwise_not(x["m"])))))
        out = F.bitwise_not(g) if op in ("lt", "le") else g
    return out.bitwiseAND(validity(spec, live))
