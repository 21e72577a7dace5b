"""Quantities of the theory on a state's rows (id, z, f, dual), and checks of a trace."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factorclust.functions import vectors
from factorclust.functions.theory import smoothness_bound


def _sums(rows: DataFrame, r: int | None = None) -> np.ndarray:
    got = {x.j: x.s for x in rows.select(F.posexplode("f").alias("j", "v")).groupBy("j").agg(F.sum("v").alias("s")).collect()}  # r rows
    return np.array([got[j] for j in sorted(got)])


def _array(v) -> F.Column:
    return F.array(*[F.lit(float(x)) for x in v])


def _moment(rows: DataFrame) -> np.ndarray:
    """z transposed times f; d x r numbers."""
    pairs = rows.select(F.posexplode("z").alias("i", "a"), "f").select("i", "a", F.posexplode("f").alias("j", "b")).groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("s")).collect()
    out = np.zeros((max(p.i for p in pairs) + 1, max(p.j for p in pairs) + 1))
    for p in pairs:
        out[p.i, p.j] = p.s
    return out


def objective(rows: DataFrame) -> float:
    return -float((_moment(rows) ** 2).sum())


def in_domain(rows: DataFrame, k: int) -> DataFrame:
    """(least entry, squared norm, ok)."""
    return rows.agg(F.min(F.array_min("f")).alias("least"), F.sum(vectors.norm2(F.col("f"))).alias("norm2")).withColumn("ok", (F.col("least") >= 0) & (F.abs(F.col("norm2") - k) < 1e-9 * k))


def lagrangian(rows: DataFrame, n: int, penalty: float, normalised: bool = True) -> DataFrame:
    """The augmented Lagrangian; the stored dual is the multiplier over root n, so it meets the plain residual."""
    colsum = _array(_sums(rows))
    weight = penalty / (n if normalised else 1)
    resid = vectors.dot(F.col("f"), colsum) - 1
    return rows.select("dual", resid.alias("q")).agg((F.lit(objective(rows)) + F.sum(F.col("dual") * F.col("q")) + 0.5 * weight * F.sum(F.col("q") * F.col("q"))).alias("lagrangian"))


def gradient_rows(rows: DataFrame, n: int, penalty: float, r: int, normalised: bool = True) -> DataFrame:
    """(id, gradient): formed explicitly, for reference only."""
    p, pull = _sums(rows), _moment(rows)
    weight = penalty / (n if normalised else 1)
    with_eff = rows.withColumn("eff", F.col("dual") + weight * (vectors.dot(F.col("f"), _array(p)) - 1))
    s = {x.j: x.s for x in with_eff.select(F.posexplode("f").alias("j", "v"), "eff").groupBy("j").agg(F.sum(F.col("v") * F.col("eff")).alias("s")).collect()}  # r rows
    entry = [-2 * vectors.dot(F.col("z"), _array(pull[:, j])) + F.col("eff") * float(p[j]) + float(s[j]) for j in range(r)]
    return with_eff.select("id", F.array(*entry).alias("gradient"))


def penalty_gradient_norm(rows: DataFrame, n: int, penalty: float, normalised: bool) -> float:
    """The norm of the penalty's part of the gradient: it grows with n unless residual and weight are scaled."""
    p = _sums(rows)
    weight = penalty / (n if normalised else 1)
    eff = rows.withColumn("eff", weight * (vectors.dot(F.col("f"), _array(p)) - 1))
    s = {x.j: x.s for x in eff.select(F.posexplode("f").alias("j", "v"), "eff").groupBy("j").agg(F.sum(F.col("v") * F.col("eff")).alias("s")).collect()}
    t = eff.agg(F.sum(F.col("eff") * F.col("eff")).alias("e2"), F.sum("eff").alias("e1")).first()
    sv = np.array([s[j] for j in sorted(s)])
    return float(np.sqrt(t.e2 * (p @ p) + 2 * t.e1 * (p @ sv) + n * (sv @ sv)))


def descent_gaps(values: list[float], moves: list[float], step: float, dual_norm: float, penalty: float, k: int) -> list[float]:
    """For each step: the fall of the Lagrangian less what the bound promises; not negative for a step below it."""
    bound = smoothness_bound(dual_norm, penalty, k)
    share = (1 - step * bound) / (2 * step)
    return [a - b - share * m * m * k for a, b, m in zip(values, values[1:], moves, strict=False)]


def movement_series(trace: DataFrame) -> DataFrame:
    """Running sum of squared movement over a trace; bounded for a fixed dual and a small step."""
    w = Window.partitionBy("run_id").orderBy("iter").rowsBetween(Window.unboundedPreceding, 0)
    return trace.withColumn("total", F.sum(F.col("move") * F.col("move")).over(w))


def movement_shortcut(scale: float, no: float, k: int) -> float:
    """Movement with both squared norms taken as K; it errs where the iterates come to rest."""
    return float(np.sqrt(max(2 * k - 2 * scale * no, 0.0) / k))


def association_gap(points: DataFrame, r: int, tile_rows: int = 2_048) -> DataFrame:
    """(gap): the largest difference between Z (Z'F) and (Z Z') F, for the points Z normalised and the portable start F of rank r.

    The n x n inner products are made as tiles meet tiles, some rows of a tile at a time, so a task holds tile_rows^2 / 8
    of them; for each tile, r numbers a row and partition are added up.
    """
    from factorclust.operators import solver
    from factorclust.operators.kernel import Config
    from factorclust.operators.normalize import column_stats, gram_matrix

    spark = points.sparkSession
    stats = column_stats(points)
    n, d, mean = stats["n"], stats["d"], stats["mean"]
    sigma = float(np.sqrt(np.linalg.eigvalsh(gram_matrix(points, mean))[-1]))
    parts = max(spark.sparkContext.defaultParallelism, n // (8 * tile_rows))
    state, _ = solver._cut(solver.build_tiles(points, mean, sigma, Config(k=r, rank=r), tile_rows, parts), solver.state_folder(spark))
    pull = solver.add_up(state, d, r).pull
    schema = "tile long, part binary"
    row = lambda tile, v: pa.RecordBatch.from_arrays([pa.array([tile], pa.int64()), pa.array([np.ascontiguousarray(v).tobytes()], pa.binary())], names=["tile", "part"])
    rows_of = lambda b, column, i, width: np.frombuffer(b.column(column)[i].as_buffer()).reshape(-1, width)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                yield row(b.column(0)[i].as_py(), -(rows_of(b, 1, i, d) @ pull))

    def second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: dict[int, np.ndarray] = {}
        for b in batches:
            for i in range(b.num_rows):
                tile, za, zb, f = b.column(0)[i].as_py(), rows_of(b, 1, i, d), rows_of(b, 2, i, d), rows_of(b, 3, i, r)
                many = max(1, tile_rows // 8)
                done[tile] = done.get(tile, 0.0) + np.concatenate([(za[at : at + many] @ zb.T) @ f for at in range(0, len(za), many)])
        for tile, v in done.items():
            yield row(tile, v)

    def gap(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(v.as_buffer()) for v in t.column(1))
        return pa.table({"gap": [float(np.abs(total).max())]})

    mine = state.select("tile", "z")
    met = mine.crossJoin(state.select(F.col("z").alias("other"), "raw")).mapInArrow(second, schema)
    return mine.mapInArrow(first, schema).unionByName(met).groupBy("tile").applyInArrow(gap, "gap double").agg(F.max("gap").alias("gap"))
