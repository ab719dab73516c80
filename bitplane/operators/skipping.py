"""Data skipping by word headers: extremes and Bloom filters."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import balanced, lit
from ..plans import blooms
from ..plans.spec import Manifest


def zone(node: tuple, manifest: Manifest) -> Column | None:
    """Blocks that may hold rows, as plain comparisons on header columns, which reach the Parquet reader's statistics; None if all may."""
    if node[0] in ("and", "or"):
        parts = [zone(x, manifest) for x in node[1]]
        if node[0] == "or":
            return None if not parts or any(p is None for p in parts) else balanced(lambda a, b: a | b, parts)
        parts = [p for p in parts if p is not None]
        return balanced(lambda a, b: a & b, parts) if parts else None
    if node[0] == "none":
        return F.lit(False)
    if node[0] == "set" and not node[3]:
        return (F.col(f"{node[1]}__mn") <= F.lit(node[2][-1]).cast("long")) & (F.col(f"{node[1]}__mx") >= F.lit(node[2][0]).cast("long"))
    if node[0] != "cmp":
        return None
    _, name, op, k = node
    mn, mx, c = F.col(f"{name}__mn"), F.col(f"{name}__mx"), F.lit(k).cast("long")
    return {"gt": mx > c, "ge": mx >= c, "lt": mn < c, "le": mn <= c, "eq": (mn <= c) & (mx >= c), "ne": (mn != c) | (mx != c)}[op]


def zone_filter(words: DataFrame, manifest: Manifest, node: tuple) -> DataFrame:
    """Extremes first, then Bloom filters."""
    for cond in (zone(node, manifest), bloom(node, manifest)):
        words = words if cond is None else words.where(cond)
    return words


def skipped(words: DataFrame, manifest: Manifest, node: tuple) -> DataFrame:
    """Words in all and words left by extremes and Bloom filters."""
    conds = [c for c in (zone(node, manifest), bloom(node, manifest)) if c is not None]
    cond = balanced(lambda a, b: a & b, conds) if conds else None
    return words.agg(F.count(F.lit(1)).alias("words"), F.coalesce(F.count_if(cond if cond is not None else F.lit(True)), lit(0)).alias("kept"))


#: Constants of an IN list up to which each is tested against the words' Bloom filters.
BLOOM_CONSTANTS = 64


def bloom(node: tuple, manifest: Manifest) -> Column | None:
    """Words that may hold a constant of an equality or IN by their headers' Bloom filters; None if all may."""
    if node[0] == "and":
        parts = [p for p in (bloom(x, manifest) for x in node[1]) if p is not None]
        return balanced(lambda a, b: a & b, parts) if parts else None
    if node[0] == "or":
        parts = [bloom(x, manifest) for x in node[1]]
        return None if not parts or len(parts) > BLOOM_CONSTANTS or any(p is None for p in parts) else balanced(lambda a, b: a | b, parts)
    if node[0] == "cmp" and node[2] == "eq" and manifest[node[1]].bloom:
        return blooms.may_hold(manifest[node[1]], node[3])
    if node[0] == "set" and not node[3] and manifest[node[1]].bloom and len(node[2]) <= BLOOM_CONSTANTS:
        return balanced(lambda a, b: a | b, [blooms.may_hold(manifest[node[1]], k) for k in node[2]])
    return None
