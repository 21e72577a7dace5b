"""Random numbers from integer arithmetic that Spark, NumPy and DuckDB do alike.

A draw depends on an id, a column number and a seed alone, so it is the same on any partitioning.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The modulus 2^31 - 1 and odd multipliers below 2^20.
MODULUS, BY_ID, BY_COLUMN, BY_SEED = 2_147_483_647, 1_000_003, 742_939, 104_729
#: Uniforms summed for one nearly normal draw.
TERMS = 12


def mix(i: Column, j: Column | int, seed: int) -> Column:
    """An integer in 0..MODULUS-1: two squarings of a linear form of id, column and seed."""
    p = F.lit(MODULUS).cast("long")
    i, j = F.pmod(i.cast("long"), p), (F.lit(j) if isinstance(j, int) else j).cast("long")
    x = F.pmod(i * BY_ID + j * BY_COLUMN + (seed + 1) * BY_SEED, p)
    x = F.pmod(x * x + i + j * 7 + 3, p)
    return F.pmod(x * x + j * BY_ID + i * 5 + seed, p)


def mix_np(i: np.ndarray, j: np.ndarray | int, seed: int) -> np.ndarray:
    i, j = np.asarray(i, np.int64) % MODULUS, np.asarray(j, np.int64)
    x = (i * BY_ID + j * BY_COLUMN + (seed + 1) * BY_SEED) % MODULUS
    x = (x * x + i + j * 7 + 3) % MODULUS
    return (x * x + j * BY_ID + i * 5 + seed) % MODULUS


def mix_sql(i: str, j: str | int, seed: int) -> str:
    i = f"((({i})::BIGINT) % {MODULUS})"
    j = f"(({j})::BIGINT)"
    x = f"(({i} * {BY_ID} + {j} * {BY_COLUMN} + {(seed + 1) * BY_SEED}) % {MODULUS})"
    x = f"(({x} * {x} + {i} + {j} * 7 + 3) % {MODULUS})"
    return f"(({x} * {x} + {j} * {BY_ID} + {i} * 5 + {seed}) % {MODULUS})"


def uniform(i: Column, j: Column | int, seed: int) -> Column:
    """A draw in (0, 1)."""
    return (mix(i, j, seed).cast("double") + 0.5) / float(MODULUS)


def uniform_np(i: np.ndarray, j: np.ndarray | int, seed: int) -> np.ndarray:
    return (mix_np(i, j, seed) + 0.5) / float(MODULUS)


def uniform_sql(i: str, j: str | int, seed: int) -> str:
    return f"(({mix_sql(i, j, seed)}::DOUBLE + 0.5) / {float(MODULUS)})"


def normal_np(i: np.ndarray, j: np.ndarray, seed: int) -> np.ndarray:
    """Nearly normal: TERMS uniforms less their mean."""
    return sum(uniform_np(i, j * TERMS + t, seed) for t in range(TERMS)) - TERMS / 2


def normal(i: Column, j: Column | int, seed: int) -> Column:
    j = F.lit(j) if isinstance(j, int) else j
    total = uniform(i, j * TERMS, seed)
    for t in range(1, TERMS):
        total = total + uniform(i, j * TERMS + t, seed)
    return total - TERMS / 2
