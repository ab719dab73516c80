"""Cost and accuracy measures; plain arithmetic on sizes that a manifest knows."""

from __future__ import annotations

import math
import statistics

def width(largest: int) -> int:
    """Planes for values up to ``largest``; one at least."""
    return max(1, int(largest).bit_length())


def compression_ratio(b: float, base: int = 32) -> float:
    return base / b


def block_bytes(n: int, b: int, w: int = 64, header: int = 0) -> int:
    """Bytes of a block of n values in b planes, each padded to registers of w bits."""
    return header + b * -(-n // w) * w // 8


def bytes_per_value(b: float) -> float:
    return b / 8


def plane_passes(kind: str, b: int, k: int = 1, lo_at_minimum: bool = False) -> int:
    if kind == "between":
        return b if lo_at_minimum else 2 * b
    return {"eq": b, "ne": b, "gt": b, "ge": b, "lt": b, "le": b, "in": k * b}[kind]


def plane_ops(n: int, b: float, w: int = 64) -> float:
    """Register operations of one predicate over n values."""
    return b * n / w


def beats_scalar(b: float, w: int) -> bool:
    return b < w


def compound_ops(bs: list[float], n: int, w: int = 64) -> float:
    """All columns' planes and one merge between neighbours."""
    return (sum(bs) + len(bs) - 1) * n / w


def working_set_bytes(n: int, b: int) -> int:
    return n * b // 8


def bandwidth(bytes_: float, seconds: float) -> float:
    return bytes_ / seconds


def break_even(encode: float, scalar: float, sliced: float) -> float:
    """Scans after which encoding has paid; infinite if a sliced scan is not faster."""
    return encode / (scalar - sliced) if scalar > sliced else math.inf


def total_cost(scans: int, encode: float, sliced: float) -> float:
    return encode + scans * sliced


def spread(rates: list[float]) -> float:
    """Largest relative deviation between rates."""
    return max(rates) / min(rates) - 1


def expected_speedup(bs: list[float], scalar_ops: float = 1.0, w: int = 64) -> float:
    """Speed-up of a compound over scalar code: the mean of its columns weighted by their planes."""
    return sum(scalar_ops * w / b * b for b in bs) / sum(bs)


def median_of(runs: list[float], warm_up: int = 5) -> float:
    return statistics.median(runs[warm_up:] or runs)


def _beta_share(a: float, b: float, x: float) -> float:
    """The regularised incomplete beta function, by its continued fraction (modified Lentz)."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - _beta_share(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    tiny = 1e-300
    c, d = 1.0, 1 / max(1 - (a + b) * x / (a + 1), tiny)
    out = d
    for m in range(1, 500):
        for up in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + up * d or tiny)
            c = 1 + up / c or tiny
            out *= c * d
        if abs(c * d - 1) < 1e-15:
            break
    return front * out


def t_quantile(degrees: int, level: float) -> float:
    """The two-sided Student t quantile, by bisection."""
    lo, hi = 0.0, 1e6
    for _ in range(200):
        mid = (lo + hi) / 2
        outside = _beta_share(degrees / 2, 0.5, degrees / (degrees + mid * mid))
        lo, hi = (mid, hi) if outside > 1 - level else (lo, mid)
    return (lo + hi) / 2


def mean_ci(xs: list[float], level: float = 0.999) -> tuple[float, float]:
    """Mean and half width of its confidence interval."""
    return statistics.fmean(xs), t_quantile(len(xs) - 1, level) * statistics.stdev(xs) / math.sqrt(len(xs))


def economics(values: float, bytes_value: float, node_gb: float, usd_hour: float, hours_year: float = 8 * 250) -> dict[str, float]:
    """Memory, nodes and money to hold a column in memory."""
    gb = values * bytes_value / 1e9
    nodes = max(1, math.ceil(gb / node_gb))
    return {"gb": gb, "nodes": nodes, "usd_hour": nodes * usd_hour, "usd_year": nodes * usd_hour * hours_year}


def cluster_seconds(partitions: int, ms: float) -> float:
    return partitions * ms / 1000


def encode_rate(ms: float, rows: float) -> float:
    """Milliseconds a million rows."""
    return ms / (rows / 1e6)
