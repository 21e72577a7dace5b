"""The distributed fit with points and state in two tables, bucketed alike by tile.

The points are written once; an iteration reads them and the last state bucket by bucket, without a shuffle
on either side, and writes the next state. Two generations of the state exist at a time, so a lost
executor costs the buckets it held and a crash leaves the last whole generation. For points that are too
many to be carried in the cached state.
"""

from __future__ import annotations

import time
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from factorclust.operators.kernel import Config, Control, Driver, fused_step
from factorclust.operators.normalize import column_stats, gram_matrix
from factorclust.operators.solver import TILE_ROWS, Model, add_up, build_tiles, matrix

POINTS = ("tile", "ids", "z")
STATE = "tile long, rows int, raw binary, dual binary, sums array<double>"


def bucketed(df: DataFrame, buckets: int, what: str) -> tuple[DataFrame, str]:
    """(a table of ``buckets`` buckets by tile, sorted by it; its name)."""
    name = f"factorclust_{what}_{uuid.uuid4().hex[:12]}"
    df.write.bucketBy(buckets, "tile").sortBy("tile").saveAsTable(name)
    return df.sparkSession.table(name), name


def sweep(points: DataFrame, state: DataFrame, control: Control, d: int, r: int) -> DataFrame:
    """The next state from both tables; each group is one tile."""
    held = points.sparkSession.sparkContext.broadcast(control)

    def step(x: pa.Table, s: pa.Table) -> pa.Table:
        dual = np.frombuffer(s.column("dual")[0].as_buffer())
        z, raw = (matrix(c[0].as_buffer(), len(dual), w) for c, w in ((x.column("z"), d), (s.column("raw"), r)))
        new, dual, sums = fused_step(z, raw, dual, held.value)
        return pa.table({"tile": s.column("tile"), "rows": s.column("rows"), "raw": pa.array([new.tobytes()], pa.binary()), "dual": pa.array([dual.tobytes()], pa.binary()), "sums": pa.array([sums.pack().tolist()], pa.list_(pa.float64()))})

    return points.groupBy("tile").cogroup(state.groupBy("tile")).applyInArrow(step, STATE)


def fit(points: DataFrame, cfg: Config, buckets: int, tile_rows: int = TILE_ROWS) -> Model:
    """As solver.fit_distributed, with the same iterates."""
    stats = column_stats(points)
    n, d, mean = stats["n"], stats["d"], stats["mean"]
    if not 1 <= cfg.k <= n:
        raise ValueError(f"{cfg.k} clusters of {n} points")
    sigma = float(np.sqrt(np.linalg.eigvalsh(gram_matrix(points, mean))[-1])) if cfg.normalise else 1.0
    if cfg.normalise and not sigma > 1e-150:
        raise ValueError("all points are equal")
    spark = points.sparkSession
    first, first_name = bucketed(build_tiles(points, mean, sigma, cfg, tile_rows), buckets, "first")
    fixed, _ = bucketed(first.select(*POINTS), buckets, "points")
    state, name = bucketed(first.select("tile", "rows", "raw", "dual", "sums"), buckets, "state")
    driver = Driver(cfg, n, d)
    control: Control | None = driver.first(add_up(first.select("sums"), d, cfg.r))
    spark.sql(f"drop table {first_name}")
    scale = control.scale
    while control is not None:
        began = time.perf_counter()
        new, new_name = bucketed(sweep(fixed, state, control, d, cfg.r), buckets, "state")
        nxt = driver.advance(add_up(new.select("sums"), d, cfg.r), time.perf_counter() - began)
        if driver.status == "breakdown":
            break
        spark.sql(f"drop table {name}")
        state, name, scale, control = new, new_name, driver.scale, nxt
    both = fixed.join(state, "tile").select("tile", "rows", "ids", "z", "raw", "dual", "sums")
    return Model(both, scale, driver.gram, driver.trace, driver.status, cfg, mean, sigma, driver.bound_ok)


def drop_tables(spark: SparkSession) -> None:
    """Drops what fits have left in this session's catalog."""
    for t in spark.catalog.listTables():
        if t.name.startswith("factorclust_") and not t.isTemporary:
            spark.sql(f"drop table if exists {t.name}")
