"""Binds predicates to encoded columns: constants become ordinals, out-of-domain parts verdicts.

The result is a small tree of tuples that all engines read:
("and" | "or", [nodes]), ("cmp", column, op, ordinal), ("cols", op, a, b),
("set", column, ordinals, negated), ("valid", column), ("null", column), ("none",).
"""

from __future__ import annotations

import re

from .predicates import And, Between, Cmp, CmpCols, In, IsNull, Like, Or, Pred, normalise
from .spec import ColumnSpec, Manifest

NONE = ("none",)

#: Plane reads up to which an IN list is evaluated on planes rather than by hash on values.
IN_PASSES = 256


def in_strategy(planes: int, k: int) -> str:
    return "runs" if planes * k <= IN_PASSES else "hash"


def bind(p: Pred, manifest: Manifest, in_strategy: str = "auto") -> tuple:
    return _bind(normalise(p), manifest, in_strategy)


def both(*parts: tuple) -> tuple:
    flat = [x for p in parts for x in (p[1] if p[0] == "and" else [p])]
    if NONE in flat:
        return NONE
    return flat[0] if len(flat) == 1 else ("and", flat)


def either(*parts: tuple) -> tuple:
    flat = [x for p in parts for x in (p[1] if p[0] == "or" else [p]) if x != NONE]
    return NONE if not flat else flat[0] if len(flat) == 1 else ("or", flat)


def compare(spec: ColumnSpec, op: str, x) -> tuple:
    """One comparison; values beyond the dataset's range need no planes."""
    if x is None:
        return NONE
    op, k = spec.codec.bound(op, x)
    return verdict(spec, op, k)


def verdict(spec: ColumnSpec, op: str, k: int | None) -> tuple:
    every = ("valid", spec.name)
    if op in ("all", "none"):
        return every if op == "all" else NONE
    lo, hi = spec.lo, spec.hi
    if lo is None or hi is None:
        return ("cmp", spec.name, op, k)
    if k < lo:
        return every if op in ("gt", "ge", "ne") else NONE
    if k > hi:
        return every if op in ("lt", "le", "ne") else NONE
    if op == "ge" and k <= lo or op == "le" and k >= hi:
        return every
    if op == "lt" and k <= lo or op == "gt" and k >= hi:
        return NONE
    return ("cmp", spec.name, op, k)


def runs(codes: list[int]) -> list[tuple[int, int]]:
    """Maximal runs of neighbouring ordinals."""
    out: list[tuple[int, int]] = []
    for k in sorted(set(codes)):
        if out and k == out[-1][1] + 1:
            out[-1] = (out[-1][0], k)
        else:
            out.append((k, k))
    return out


def in_set(spec: ColumnSpec, codes: list[int], negated: bool, strategy: str) -> tuple:
    """Equality per ordinal, one range per run of neighbours where that takes fewer planes, or a hash set of ordinals.

    ``auto`` takes the hash set for lists that need more than IN_PASSES plane reads.
    """
    parts = []
    codes = sorted({k for k in codes if (spec.lo is None or k >= spec.lo) and (spec.hi is None or k <= spec.hi)})
    pieces = runs(codes) if strategy != "each" else [(k, k) for k in codes]
    if codes and (strategy == "hash" or strategy == "auto" and in_strategy(spec.planes, sum(min(b - a + 1, 2) for a, b in pieces)) == "hash"):
        return ("set", spec.name, tuple(codes), negated)
    for a, b in pieces:
        if b - a < 2:
            parts += [verdict(spec, "ne" if negated else "eq", k) for k in range(a, b + 1)]
        elif negated:
            parts.append(either(verdict(spec, "lt", a), verdict(spec, "gt", b)))
        else:
            parts.append(both(verdict(spec, "ge", a), verdict(spec, "le", b)))
    if negated:
        return both(*parts) if parts else ("valid", spec.name)
    return either(*parts)


def _bind(p: Pred, manifest: Manifest, strategy: str) -> tuple:
    if isinstance(p, And):
        return both(*(_bind(q, manifest, strategy) for q in p.parts))
    if isinstance(p, Or):
        return either(*(_bind(q, manifest, strategy) for q in p.parts))
    spec = manifest[p.col]
    if isinstance(p, Cmp):
        return compare(spec, p.op, p.const)
    if isinstance(p, Between):
        if p.negated:
            return either(compare(spec, "lt", p.lo), compare(spec, "gt", p.hi))
        return both(compare(spec, "ge", p.lo), compare(spec, "le", p.hi))
    if isinstance(p, In):
        if p.negated and None in p.consts:
            return NONE
        exact = [spec.codec.bound("eq", x) for x in p.consts if x is not None]
        return in_set(spec, [k for op, k in exact if op == "eq"], p.negated, strategy)
    if isinstance(p, Like):
        test = re.compile(like_regex(p.pattern), re.S).fullmatch
        return in_set(spec, spec.codec.matching(test), p.negated, "auto")
    if isinstance(p, IsNull):
        return ("valid" if p.negated else "null", spec.name)
    if isinstance(p, CmpCols):
        other = manifest[p.other]
        if not (spec.literal and other.literal):
            raise ValueError("column comparisons need literal biases (none or global)")
        if type(spec.codec) is not type(other.codec) or getattr(spec.codec, "scale", 0) != getattr(other.codec, "scale", 0) or getattr(spec.codec, "values", ()) != getattr(other.codec, "values", ()):
            raise ValueError("column comparisons need equal codecs")
        return ("cols", p.op, p.col, p.other)
    raise TypeError(f"not a predicate: {p!r}")


def like_regex(pattern: str) -> str:
    out, i = [], 0
    while i < len(pattern):
        c = pattern[i]
        if c == "\\" and i + 1 < len(pattern):
            i += 1
            out.append(re.escape(pattern[i]))
        else:
            out.append({"%": ".*", "_": "."}.get(c, re.escape(c)))
        i += 1
    return "".join(out)


def passes(node: tuple, manifest: Manifest) -> int:
    """Plane reads of a bound predicate."""
    if node[0] in ("and", "or"):
        return sum(passes(x, manifest) for x in node[1])
    if node[0] in ("cmp", "set"):
        return manifest[node[1]].planes
    if node[0] == "cols":
        return manifest[node[2]].planes + manifest[node[3]].planes
    return 0
