"""Cost-based choices from the manifest alone; no scan."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import metrics
from .binding import IN_PASSES, in_strategy, passes  # noqa: F401
from .predicates import And, Like, Pred, columns, leaves
from .spec import Manifest

#: Values up to which a wide column is better held as dictionary codes.
DICTIONARY = 4096


def estimate(node: tuple, manifest: Manifest, w: int = 64) -> dict:
    reads = passes(node, manifest)
    rows = manifest.rows or 0
    merges = max(0, sum(1 for _ in _leaves(node)) - 1)
    return {"passes": reads, "merges": merges, "ops": (reads + merges) * -(-rows // w), "bytes": reads * rows // 8}


def _leaves(node: tuple):
    if node[0] in ("and", "or"):
        for x in node[1]:
            yield from _leaves(x)
    else:
        yield node


def choose_representation(b: int, distinct: int | None = None, point_lookups: bool = False, scans: float = math.inf, break_even: float = 0.0, most: int = DICTIONARY) -> str:
    """sliced, dict (sliced codes of a dictionary) or plain: narrow columns that are scanned often are sliced; point lookups and wide ones stay plain."""
    if point_lookups or scans < break_even:
        return "plain"
    if b <= 16:
        return "sliced"
    if distinct is not None and distinct <= most:
        return "dict"
    return "sliced" if b < 32 else "plain"


def representation_table(df: DataFrame, cols: dict[str, Column]) -> DataFrame:
    """column, planes, distinct (approximate), choice: one row for each of the named integer expressions, from one scan."""
    aggs = [f.alias(f"{c}__{n}") for c, x in cols.items() for n, f in (("lo", F.min(x).cast("long")), ("hi", F.max(x).cast("long")), ("k", F.approx_count_distinct(x)))]
    got = df.agg(*aggs).first()
    out = []
    for c in cols:
        planes = metrics.width((got[f"{c}__hi"] or 0) - (got[f"{c}__lo"] or 0))
        out.append((c, planes, got[f"{c}__k"], choose_representation(planes, got[f"{c}__k"])))
    return df.sparkSession.createDataFrame(out, "column string, planes int, distinct long, choice string")


def should_encode(encode: float, scalar: float, sliced: float, expected_scans: float) -> bool:
    """Data read once is never worth encoding."""
    return expected_scans > 1 and expected_scans >= metrics.break_even(encode, scalar, sliced)


def order_conjuncts(p: Pred, manifest: Manifest) -> Pred:
    """Narrow columns first; matters only where blocks are skipped."""
    if not isinstance(p, And):
        return p
    return And(tuple(sorted(p.parts, key=lambda q: sum(manifest[c].planes for c in columns(q)))))


def split(p: Pred, manifest: Manifest) -> tuple[Pred | None, list[Pred]]:
    """The conjuncts that encoded columns decide, and the rest."""
    parts = p.parts if isinstance(p, And) else (p,)
    def sliceable(q: Pred) -> bool:
        return columns(q) <= {s.name for s in manifest.columns} and all(not isinstance(x, Like) or getattr(manifest[x.col].codec, "values", None) is not None for x in leaves(q))
    mine = tuple(q for q in parts if sliceable(q))
    return (And(mine) if len(mine) > 1 else mine[0] if mine else None), [q for q in parts if not sliceable(q)]


def calibrate(count: Callable[[str], DataFrame], engines: tuple[str, ...] = ("catalyst", "numpy"), runs: int = 3) -> dict[str, float]:
    """Seconds of a count on each engine (the best of a few warm runs), for ``kernel_for``."""
    took = {}
    for engine in engines:
        times = []
        for _ in range(runs):
            start = time.perf_counter()
            count(engine).collect()
            times.append(time.perf_counter() - start)
        took[engine] = min(times[1:] or times)
    return took


def kernel_for(measured: dict[str, float] | None = None) -> str:
    """The engine of the session: generated code unless a calibration run has another one ahead."""
    return min(measured, key=measured.get) if measured else "catalyst"
