"""Column means, the second moment, and the spectral norm of centred points."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def column_stats(points: DataFrame) -> dict:
    """Count, width and mean; rows of different widths are an error."""
    w = points.agg(F.count(F.lit(1)).alias("n"), F.min(F.size("x")).alias("lo"), F.max(F.size("x")).alias("hi")).first()
    if not w.n or w.lo != w.hi or w.lo < 1:
        raise ValueError(f"points need one width, found {w.lo} to {w.hi} in {w.n} rows")
    mean = np.zeros(w.lo)
    for r in points.select(F.posexplode("x").alias("j", "v")).groupBy("j").agg(F.avg("v").alias("m")).collect():  # d rows
        mean[r.j] = r.m
    return {"n": w.n, "d": w.lo, "mean": mean}


def center(points: DataFrame, mean: np.ndarray) -> DataFrame:
    """Narrow: each row less the mean."""
    m = F.array(*[F.lit(float(v)) for v in mean])
    return points.withColumn("x", F.zip_with("x", m, lambda a, b: a - b))


def gram_matrix(points: DataFrame, mean: np.ndarray) -> np.ndarray:
    """The d x d second moment of the centred points; each task sends d rows."""
    d = len(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = np.zeros((d, d))
        for b in batches:
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d) - mean
            g += x.T @ x
        yield pa.RecordBatch.from_pydict({"i": np.arange(d), "row": [v.tolist() for v in g]})

    rows = points.select("x").mapInArrow(run, "i long, row array<double>").select("i", F.posexplode("row").alias("j", "v")).groupBy("i", "j").agg(F.sum("v").alias("v")).collect()  # d^2 rows
    out = np.zeros((d, d))
    for r in rows:
        out[r.i, r.j] = r.v
    return out


def spectral_norm(points: DataFrame, mean: np.ndarray, how: str = "gram", iters: int = 100, tol: float = 1e-10) -> float:
    """The largest singular value of the centred points: by the second moment, or by power steps for wide rows."""
    if how == "gram":
        s = float(np.sqrt(max(np.linalg.eigvalsh(gram_matrix(points, mean))[-1], 0.0)))
    else:
        v = np.ones(len(mean)) / np.sqrt(len(mean))
        s = 0.0
        for _ in range(iters):
            w = _power_step(points, mean, v)
            norm = float(np.linalg.norm(w))
            if norm == 0:
                break
            v, old, s = w / norm, s, float(np.sqrt(norm))
            if abs(s - old) <= tol * s:
                break
    if not s > 1e-150:
        raise ValueError("all points are equal")
    return s


def _power_step(points: DataFrame, mean: np.ndarray, v: np.ndarray) -> np.ndarray:
    d = len(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(d)
        for b in batches:
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d) - mean
            total += x.T @ (x @ v)
        yield pa.RecordBatch.from_pydict({"j": np.arange(d), "s": total})

    out = np.zeros(d)
    for r in points.select("x").mapInArrow(run, "j long, s double").groupBy("j").agg(F.sum("s").alias("s")).collect():  # d rows
        out[r.j] = r.s
    return out
