"""Lloyd's iteration: the three baselines, careful seeding, restarts, and a sample-then-assign variant.

``norm`` stops when the summed centroid movement is within the tolerance, ``squared`` when the sum of its
squares is, ``max`` when the largest is, ``objective`` when the within sum of squares falls by no more than that share
of itself; ``labels`` when no label changes. Ties go to the lowest
centroid; an empty cluster keeps its centroid.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.functions import portable
from factorclust.operators.kernel import nearest

TOLERANCE = 1e-4
#: Iterations of the capped baseline.
CAP = 2000


@dataclass
class Result:
    labels: np.ndarray
    centroids: np.ndarray
    wcss: float
    iters: int
    seconds: float
    status: str


def movement(old: np.ndarray, new: np.ndarray, rule: str) -> float:
    far = np.sqrt(((new - old) ** 2).sum(1))
    return float((far**2).sum() if rule == "squared" else far.max() if rule == "max" else np.sqrt((far**2).sum()))


def fall(before: float, now: float) -> float:
    """The share of itself by which the within sum of squares has fallen."""
    return float("inf") if before == np.inf else (before - now) / max(before, 1e-300)


def seed_points(x: np.ndarray, k: int, seed: int, seeding: str = "points") -> np.ndarray:
    """k rows: the ones with the least draws, or one after the other by squared distance."""
    draw = np.random.default_rng(seed)
    if seeding == "points":
        return x[draw.choice(len(x), k, replace=False)].copy()
    chosen = [int(draw.integers(len(x)))]
    d2 = ((x - x[chosen[0]]) ** 2).sum(1)
    while len(chosen) < k:
        total = d2.sum()
        pick = int(draw.integers(len(x))) if total <= 0 else int(np.searchsorted(np.cumsum(d2), draw.random() * total, "right").clip(0, len(x) - 1))
        chosen.append(pick)
        d2 = np.minimum(d2, ((x - x[pick]) ** 2).sum(1))
    return x[chosen].copy()


def sums_by(labels: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """The k sums of rows, each added up in the order of the rows."""
    return np.stack([np.bincount(labels, weights=x[:, j], minlength=k) for j in range(x.shape[1])], axis=1)


def sweep(x: np.ndarray, c: np.ndarray, columns: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """(labels, new centroids, sizes, within sum of squares against the old ones); ``columns`` may be the points laid out by column."""
    labels, d2 = nearest(x, c)
    sizes = np.bincount(labels, minlength=len(c))
    sums = sums_by(labels, x if columns is None else columns, len(c))
    return labels, moved_to(c, sums, sizes), sizes, float(d2.sum())


def moved_to(c: np.ndarray, sums: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The means; where a cluster is empty its centroid as it was."""
    return np.where(sizes[:, None] > 0, sums / np.maximum(1, sizes)[:, None], c)


def fit_local(x: np.ndarray, k: int, seed: int, stop: str = "norm", tol: float = TOLERANCE, max_iter: int = 10_000, seeding: str = "points", restarts: int = 1, start: np.ndarray | None = None) -> Result:
    if not 1 <= k <= len(x):
        raise ValueError(f"{k} clusters of {len(x)} points")
    best: Result | None = None
    columns = np.asfortranarray(x)
    for run in range(restarts):
        began = time.perf_counter()
        c = seed_points(x, k, seed + 7919 * run, seeding) if start is None else start.copy()
        before, status, last = None, "capped", np.inf
        for it in range(1, max_iter + 1):
            labels, new, _, total = sweep(x, c, columns)
            moved = fall(last, total) if stop == "objective" else movement(c, new, stop)
            last = total
            same = before is not None and (labels == before).all()
            c, before = new, labels
            if (same if stop == "labels" else moved <= tol):
                status = "converged"
                break
        labels, d2 = nearest(x, c)
        r = Result(labels, c, float(d2.sum()), it, time.perf_counter() - began, status)
        if best is None or r.wcss < best.wcss:
            best = r
    return best


def sampled(x: np.ndarray, k: int, seed: int, share: float = 0.1) -> Result:
    """Lloyd on a sample, then one assignment of all rows."""
    n = max(k, int(len(x) * share))
    pick = np.random.default_rng(seed).choice(len(x), n, replace=False)
    r = fit_local(x[pick], k, seed)
    labels, d2 = nearest(x, r.centroids)
    return Result(labels, r.centroids, float(d2.sum()), r.iters, r.seconds, r.status)


def step(points: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """One distributed sweep: (new centroids, sizes, within sum of squares). Each task sends K rows of sums."""
    held = points.sparkSession.sparkContext.broadcast(centroids)  # K x d

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = held.value
        sums, sizes, within = np.zeros_like(c), np.zeros(len(c), np.int64), 0.0
        for b in batches:
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            labels, d2 = nearest(x, c)
            sums += sums_by(labels, x, len(c))
            sizes += np.bincount(labels, minlength=len(c))
            within += float(d2.sum())
        yield pa.RecordBatch.from_pydict({"cluster": np.arange(len(c)), "sums": [s.tolist() for s in sums], "size": sizes, "within": np.full(len(c), within / len(c))})

    rows = points.select("x").mapInArrow(run, "cluster long, sums array<double>, size long, within double")
    each = rows.select("cluster", "size", "within", F.posexplode("sums").alias("at", "v")).groupBy("cluster", "at").agg(F.sum("v").alias("v"), F.sum("size").alias("size"), F.sum("within").alias("within"))
    new, sizes, within = centroids.copy(), np.zeros(len(centroids), np.int64), 0.0
    for r in each.collect():  # K x d rows
        sizes[r.cluster] = r["size"]
        within += r.within if r["at"] == 0 else 0
        if r["size"]:
            new[r.cluster, r["at"]] = r.v / r["size"]
    return new, sizes, within


def seeds(points: DataFrame, k: int, seed: int) -> np.ndarray:
    """The K points whose portable draw is least."""
    draw = portable.mix(F.col("id"), 0, seed)
    rows = points.select("x", draw.alias("u"), "id").orderBy("u", "id").limit(k).collect()
    if len(rows) < k:
        raise ValueError(f"{k} clusters of {len(rows)} points")
    return np.array([r.x for r in rows])


def fit(points: DataFrame, k: int, seed: int, stop: str = "norm", tol: float = TOLERANCE, max_iter: int = CAP, persist: StorageLevel | None = None) -> tuple[DataFrame, np.ndarray, list[dict]]:
    """(id, cluster) of all points, centroids, trace. One job a sweep; ``persist=None`` reads the source each time,
    so nothing but K centroids has to be resident."""
    if persist is not None:
        points = points.persist(persist)
    c, trace, last = seeds(points, k, seed), [], np.inf
    for it in range(1, max_iter + 1):
        began = time.perf_counter()
        new, sizes, within = step(points, c)
        moved = fall(last, within) if stop == "objective" else movement(c, new, stop)
        last = within
        trace.append({"iter": it, "moved": moved, "wcss": within, "empty": int((sizes == 0).sum()), "seconds": time.perf_counter() - began})
        c = new
        if moved <= tol:
            break
    return assign(points, c), c, trace


def assign(points: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(id, cluster, distance2) of each point, narrow."""
    held = points.sparkSession.sparkContext.broadcast(centroids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            labels, d2 = nearest(x, held.value)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(labels.astype(np.int32)), pa.array(d2)], names=["id", "cluster", "distance2"])

    return points.select("id", "x").mapInArrow(run, "id long, cluster int, distance2 double")
