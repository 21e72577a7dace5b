"""The convex relaxation for small n: objective, feasibility and a splitting solver; enumeration for tiny n."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sdp_objective(gram: np.ndarray, z: np.ndarray) -> float:
    """Minus the inner product of the points' inner products with the membership matrix."""
    return -float((gram * z).sum())


def sdp_feasibility(z: np.ndarray, k: int) -> dict[str, float]:
    """How far a matrix is from each constraint."""
    return {"psd": max(0.0, -float(np.linalg.eigvalsh((z + z.T) / 2)[0])), "nonnegative": max(0.0, -float(z.min())), "trace": abs(float(np.trace(z)) - k), "row_sums": float(np.abs(z.sum(1) - 1).max())}


def _affine(z: np.ndarray, k: int) -> np.ndarray:
    """The nearest symmetric matrix with unit row sums and trace k."""
    n = len(z)
    z = (z + z.T) / 2
    # z + u 1' + 1 u' + t I; row sums: n u + sum(u) + t = 1 - z1, trace: 2 sum(u) + n t = k - tr z
    a = 1 - z.sum(1)
    b = k - np.trace(z)
    total = (a.sum() - b) / (2 * n - 2) if n > 1 else 0.0
    t = (b - 2 * total) / n
    u = (a - total - t) / n
    return z + u[:, None] + u[None, :] + t * np.eye(n)


def solve_sdp_small(gram: np.ndarray, k: int, iters: int = 500, rho: float = 1.0) -> tuple[np.ndarray, dict[str, float]]:
    """Consensus splitting over the cone, the orthant and the affine set; n up to a few hundred."""
    n = len(gram)
    if n > 400:
        raise ValueError("the convex relaxation is solved for small n only")
    cost = -gram / max(1e-12, float(np.abs(gram).max())) / rho
    x = np.full((n, n), k / n / n) + np.eye(n) * (k / n) * (1 - 1 / n)
    parts = [x.copy() for _ in range(3)]
    duals = [np.zeros((n, n)) for _ in range(3)]
    for _ in range(iters):
        x = sum(p + u for p, u in zip(parts, duals, strict=True)) / 3 - cost / 3
        w, v = np.linalg.eigh((x - duals[0] + (x - duals[0]).T) / 2)
        parts = [(v * np.maximum(w, 0)) @ v.T, np.maximum(x - duals[1], 0), _affine(x - duals[2], k)]
        duals = [u + p - x for u, p in zip(duals, parts, strict=True)]
    return _affine(np.maximum((x + x.T) / 2, 0), k), sdp_feasibility(_affine(np.maximum((x + x.T) / 2, 0), k), k)


def brute_force_partition(points: DataFrame, k: int, most: int = 12) -> DataFrame:
    """(id, cluster) of the best partition into at most k groups, by trying all; n <= 12, K^n rows."""
    rows = points.orderBy("id").select("id", "x").limit(most + 1).collect()
    n = len(rows)
    if n > most:
        raise ValueError(f"enumeration takes at most {most} points")
    x = np.array([r.x for r in rows], float)
    g = (x @ x.T).tolist()
    code = points.sparkSession.range(k ** max(0, n - 1))  # the first point is in group 0
    digit = [F.lit(0), *[(F.floor(F.col("id") / float(k**i)) % k).cast("int") for i in range(n - 1)]]
    gain = F.lit(0.0)
    for c in range(k):
        size = sum(((d == c).cast("int") for d in digit), F.lit(0))
        inner = sum((F.when((digit[i] == c) & (digit[j] == c), g[i][j]).otherwise(0.0) for i in range(n) for j in range(n)), F.lit(0.0))
        gain = gain + F.when(size > 0, inner / size).otherwise(0.0)
    best = code.select(F.array(*digit).alias("labels"), gain.alias("gain")).orderBy(F.desc("gain"), "labels").limit(1)
    ids = F.array(*[F.lit(r.id) for r in rows])
    return best.select(F.explode(F.arrays_zip(ids.alias("id"), F.col("labels").alias("cluster"))).alias("e")).select("e.id", "e.cluster")
