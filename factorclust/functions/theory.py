"""Closed forms: the recovery threshold, its regime, the smoothness bound, and the costs of an iteration."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def cnr_squared(n: float, d: float, k: float) -> float:
    """Squared centroid-to-noise ratio at which exact recovery becomes possible."""
    log = math.log(n)
    return 4 * (1 + math.sqrt(1 + k * d / (n * log))) * log


def cnr_threshold(n: float, d: float, k: float) -> float:
    return math.sqrt(cnr_squared(n, d, k))


def cnr_squared_col(n: Column, d: Column, k: Column) -> Column:
    log = F.ln(n)
    return 4 * (1 + F.sqrt(1 + k * d / (n * log))) * log


def recovery_verdict(gamma: float, slack: float = 0.0) -> str:
    """What the theory says of a separation of gamma times the threshold."""
    return "recoverable" if gamma > 1 + slack else "impossible" if gamma < 1 - slack else "edge"


def regime_limit(n: float) -> float:
    """The order of K up to which the theory holds: log n / log log n."""
    return math.log(n) / math.log(math.log(n))


def smoothness_bound(dual_norm: float, beta: float, k: int) -> float:
    """A Lipschitz constant of the gradient on the ball of radius sqrt(K), for the multiplier of the scaled residual."""
    return 2 + 2 * dual_norm + beta * (6 * k + 2)


def flops(n: int, d: int, r: int) -> int:
    """Multiplies and adds of the two products of an iteration."""
    return 4 * n * d * r


def tiles(n: int, r: int, rows: int, columns: int) -> int:
    return -(-n // rows) * -(-r // columns)


def stats_bytes(n_tiles: int) -> int:
    """Three double sums for each tile."""
    return 24 * n_tiles


def buffers(n: int, d: int, r: int, n_tiles: int) -> dict[str, int]:
    """Bytes of each buffer of the fused form: single precision, statistics in double."""
    return {"data": 4 * n * d, "factor": 4 * n * r, "moment": 4 * d * r, "row_vectors": 16 * n, "column_vectors": 8 * r, "tile_stats": stats_bytes(n_tiles), "stats": 24}


def buffer_bytes(n: int, d: int, r: int, n_tiles: int) -> int:
    return sum(buffers(n, d, r, n_tiles).values())


def saved_bytes(n: int, r: int) -> int:
    """Two factor-sized buffers fewer."""
    return 8 * n * r


def fits(n: int, d: int, r: int, n_tiles: int, memory: int, factor_buffers: int = 1) -> bool:
    return buffer_bytes(n, d, r, n_tiles) + 4 * n * r * (factor_buffers - 1) <= memory


#: The six synthetic settings (n, d, K, r, seeds).
SETTINGS = (
    (1_000_000, 50, 20, 30, 20),
    (1_000_000, 200, 100, 300, 5),
    (10_000_000, 50, 20, 30, 20),
    (10_000_000, 200, 100, 300, 5),
    (100_000_000, 50, 20, 30, 5),
    (200_000_000, 50, 20, 60, 5),
)
