"""Predicate trees: construction, SQL text, negation normal form."""

from __future__ import annotations

import dataclasses
import re
from typing import Any

FLIP = {"eq": "ne", "ne": "eq", "gt": "le", "le": "gt", "ge": "lt", "lt": "ge"}


class Pred:
    def __and__(self, other: Pred) -> Pred:
        return And((self, other))

    def __or__(self, other: Pred) -> Pred:
        return Or((self, other))

    def __invert__(self) -> Pred:
        return Not(self)


@dataclasses.dataclass(frozen=True)
class Cmp(Pred):
    op: str
    col: str
    const: Any


@dataclasses.dataclass(frozen=True)
class Between(Pred):
    col: str
    lo: Any
    hi: Any
    negated: bool = False


@dataclasses.dataclass(frozen=True)
class In(Pred):
    col: str
    consts: tuple
    negated: bool = False


@dataclasses.dataclass(frozen=True)
class Like(Pred):
    """Prefix or general pattern on a dictionary-coded string."""

    col: str
    pattern: str
    negated: bool = False


@dataclasses.dataclass(frozen=True)
class CmpCols(Pred):
    op: str
    col: str
    other: str


@dataclasses.dataclass(frozen=True)
class IsNull(Pred):
    col: str
    negated: bool = False


@dataclasses.dataclass(frozen=True)
class And(Pred):
    parts: tuple[Pred, ...]


@dataclasses.dataclass(frozen=True)
class Or(Pred):
    parts: tuple[Pred, ...]


@dataclasses.dataclass(frozen=True)
class Not(Pred):
    part: Pred


def eq(col: str, x: Any) -> Pred:
    return Cmp("eq", col, x)


def ne(col: str, x: Any) -> Pred:
    return Cmp("ne", col, x)


def gt(col: str, x: Any) -> Pred:
    return Cmp("gt", col, x)


def ge(col: str, x: Any) -> Pred:
    return Cmp("ge", col, x)


def lt(col: str, x: Any) -> Pred:
    return Cmp("lt", col, x)


def le(col: str, x: Any) -> Pred:
    return Cmp("le", col, x)


def between(col: str, lo: Any, hi: Any) -> Pred:
    return Between(col, lo, hi)


def in_list(col: str, xs) -> Pred:
    return In(col, tuple(xs))


def prefix(col: str, start: str) -> Pred:
    return Like(col, start.replace("%", "\\%").replace("_", "\\_") + "%")


def gt_cols(a: str, b: str) -> Pred:
    return CmpCols("gt", a, b)


def is_null(col: str) -> Pred:
    return IsNull(col)


def not_null(col: str) -> Pred:
    return IsNull(col, True)


def normalise(p: Pred, negate: bool = False) -> Pred:
    """Pushes NOT down to the leaves, where it is exact for null and padding bits alike, and flattens."""
    if isinstance(p, Not):
        return normalise(p.part, not negate)
    if isinstance(p, (And, Or)):
        kind = And if isinstance(p, And) != negate else Or
        parts: list[Pred] = []
        for q in p.parts:
            q = normalise(q, negate)
            parts += q.parts if isinstance(q, kind) else [q]
        return kind(tuple(parts))
    if not negate:
        return p
    if isinstance(p, (Cmp, CmpCols)):
        return dataclasses.replace(p, op=FLIP[p.op])
    return dataclasses.replace(p, negated=not p.negated)


def columns(p: Pred) -> set[str]:
    if isinstance(p, (And, Or)):
        return set().union(*(columns(q) for q in p.parts))
    if isinstance(p, Not):
        return columns(p.part)
    return {p.col, p.other} if isinstance(p, CmpCols) else {p.col}


def leaves(p: Pred) -> list[Pred]:
    if isinstance(p, (And, Or)):
        return [x for q in p.parts for x in leaves(q)]
    return leaves(p.part) if isinstance(p, Not) else [p]


LEX = re.compile(r"\s*(?:(?P<num>-?\d+(?:\.\d+)?(?:[eE][+-]?\d+)?)|(?P<str>'(?:[^']|'')*')|(?P<op><>|!=|<=|>=|=|<|>|\(|\)|,)|(?P<word>[A-Za-z_][A-Za-z0-9_.]*))")
OPS = {"=": "eq", "<>": "ne", "!=": "ne", ">": "gt", ">=": "ge", "<": "lt", "<=": "le"}


def parse(text: str) -> Pred:
    """Reads the SQL subset: comparisons, BETWEEN, IN, LIKE, IS [NOT] NULL, AND, OR, NOT, parentheses."""
    tokens, at = [], 0
    while text[at:].strip():
        m = LEX.match(text, at)
        if not m:
            raise ValueError(f"cannot read {text[at:at + 20]!r}")
        tokens.append((m.lastgroup, m[m.lastgroup]))
        at = m.end()
    pos = 0

    def peek() -> str:
        return tokens[pos][1].lower() if pos < len(tokens) else ""

    def take(*want: str) -> tuple[str, str]:
        nonlocal pos
        if pos >= len(tokens) or want and peek() not in want:
            raise ValueError(f"expected {want or 'more'} at token {pos} of {text!r}")
        pos += 1
        return tokens[pos - 1]

    def const() -> Any:
        kind, x = take()
        if kind == "num":
            return float(x) if any(c in x for c in ".eE") else int(x)
        if kind == "str":
            return x[1:-1].replace("''", "'")
        if x.lower() in ("date", "timestamp", "timestamp_ntz"):
            return const()
        if x.lower() in ("true", "false", "null"):
            return {"true": True, "false": False, "null": None}[x.lower()]
        raise ValueError(f"not a constant: {x}")

    def either() -> Pred:
        parts = [both()]
        while peek() == "or":
            take()
            parts.append(both())
        return parts[0] if len(parts) == 1 else Or(tuple(parts))

    def both() -> Pred:
        parts = [unit()]
        while peek() == "and":
            take()
            parts.append(unit())
        return parts[0] if len(parts) == 1 else And(tuple(parts))

    def unit() -> Pred:
        if peek() == "not":
            take()
            return Not(unit())
        if peek() == "(":
            take()
            p = either()
            take(")")
            return p
        kind, col = take()
        if kind != "word":
            raise ValueError(f"expected a column, found {col!r}")
        negated = peek() == "not"
        if negated:
            take()
        word = take()[1].lower()
        if word in OPS and not negated:
            nxt = tokens[pos] if pos < len(tokens) else ("", "")
            if nxt[0] == "word" and nxt[1].lower() not in ("date", "timestamp", "timestamp_ntz", "true", "false", "null"):
                return CmpCols(OPS[word], col, take()[1])
            return Cmp(OPS[word], col, const())
        if word == "between":
            lo = const()
            take("and")
            return Between(col, lo, const(), negated)
        if word == "in":
            take("(")
            xs = [const()]
            while peek() == ",":
                take()
                xs.append(const())
            take(")")
            return In(col, tuple(xs), negated)
        if word == "like":
            return Like(col, const(), negated)
        if word == "is":
            negated = peek() == "not"
            if negated:
                take()
            take("null")
            return IsNull(col, negated)
        raise ValueError(f"not a predicate on {col}: {word}")

    p = either()
    if pos != len(tokens):
        raise ValueError(f"unread text behind token {pos} of {text!r}")
    return p
