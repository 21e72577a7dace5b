"""Fits of the factor: local, one per group of a grid, distributed in one pass an iteration, and unfused.

The distributed form keeps the points in the state row (carried), one tile a row. A sweep is a single
mapInArrow over the cached state, whose ``sums`` column alone is then added up: one job an iteration, no
join and no shuffle of anything that grows with n. The state's lineage is cut to a table now and then.
"""

from __future__ import annotations

import atexit
import itertools
import json
import shutil
import tempfile
import time
import uuid
from collections.abc import Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.operators import init, rounding
from factorclust.operators.kernel import BREAKDOWN, Config, Control, Driver, Sums, fused_step, spectral_norm, step_rows, sums_of
from factorclust.operators.normalize import column_stats, gram_matrix

#: Rows of a tile; bytes of points that a grouped fit may hold in one worker.
TILE_ROWS, LOCAL_LIMIT = 16_384, 256 << 20
#: Tiles up to which the driver adds their sums up itself.
FEW = 32


@dataclass
class Fit:
    factor: np.ndarray
    dual: np.ndarray
    trace: list[dict]
    status: str
    seconds: float
    bound_ok: bool
    snapshots: dict[int, np.ndarray] = field(default_factory=dict)


def prepare(x: np.ndarray, normalise: bool = True) -> np.ndarray:
    """Centred rows, divided by the spectral norm."""
    if not normalise:
        return np.asarray(x, float)
    z = x - x.mean(0)
    return z / spectral_norm(z)


def fit_local(x: np.ndarray, cfg: Config, ids: np.ndarray | None = None, caps: Sequence[int] = (), start: np.ndarray | None = None, prepared: bool = False, threads: int = 1) -> Fit:
    """The whole loop on one machine, by the same kernel; ``caps`` asks for labels at those iterations, ``threads`` more than 1 steps tiles of rows at once."""
    n = len(x)
    if not 1 <= cfg.k <= n:
        raise ValueError(f"{cfg.k} clusters of {n} points")
    ids = np.arange(n) if ids is None else ids
    z = x if prepared else prepare(x, cfg.normalise)
    began = time.perf_counter()
    raw = (init.raw_factor(ids, cfg.r, cfg.seed, cfg.init) if start is None else start.copy()).astype(cfg.dtype)
    z, dual = z.astype(cfg.dtype, copy=False), np.zeros(n)
    driver = Driver(cfg, n, z.shape[1])
    control: Control | None = driver.first(sums_of(z.astype(np.float64, copy=False), *[raw.astype(np.float64, copy=False)] * 2, dual))
    shots: dict[int, np.ndarray] = {}
    scale, other = control.scale, np.empty_like(raw)  # two factors by turns: the one before is kept in case of a breakdown
    with ThreadPoolExecutor(max(1, threads)) as pool:
        while control is not None:
            scale = control.scale
            s = step_rows(z, raw, dual, control, other) if threads < 2 else threaded_step(pool, threads, z, raw, dual, control, other)
            control = driver.advance(s, time.perf_counter() - began)
            if driver.status == "breakdown":
                break
            raw, other, scale = other, raw, driver.scale
            if len(driver.trace) in caps:
                shots[len(driver.trace)] = rounding.round_columns(raw * scale, cfg.k)
    f = raw * scale
    last = rounding.round_columns(f, cfg.k)
    shots |= {c: last for c in caps if c not in shots}
    return Fit(f, dual, driver.trace, driver.status, time.perf_counter() - began, driver.bound_ok, shots)


def threaded_step(pool: ThreadPoolExecutor, threads: int, z: np.ndarray, raw: np.ndarray, dual: np.ndarray, c: Control, out: np.ndarray) -> Sums:
    """The step by a piece of rows a thread; sums are added up in the order of the pieces."""
    cuts = np.linspace(0, len(z), threads + 1).astype(int)
    done = pool.map(lambda of: step_rows(z[of], raw[of], dual[of], c, out[of]).pack(), [slice(a, b) for a, b in itertools.pairwise(cuts) if b > a])
    return Sums.unpack(sum(done), z.shape[1], raw.shape[1])


def fit_threebuffer(x: np.ndarray, cfg: Config, ids: np.ndarray | None = None, prepared: bool = False) -> Fit:
    """The unfused form with a gradient and a second factor; the same iterates, for comparison."""
    n = len(x)
    ids = np.arange(n) if ids is None else ids
    z = x if prepared else prepare(x, cfg.normalise)
    w = cfg.penalty / (n if cfg.normalise else 1)
    f = init.raw_factor(ids, cfg.r, cfg.seed, cfg.init)
    f *= np.sqrt(cfg.k / (f * f).sum())
    dual, trace, status, began = np.zeros(n), [], "capped", time.perf_counter()
    step = cfg.fixed_step
    for t in range(1, cfg.max_iter + 1):
        p = f.sum(0)
        eff = dual + w * (f @ p - 1)
        gradient = -2 * z @ (z.T @ f) + np.outer(eff, p) + np.outer(np.ones(n), f.T @ eff)
        clipped = np.maximum(f - step * gradient, 0)
        norm = np.sqrt((clipped**2).sum())
        if norm <= BREAKDOWN:
            status = "breakdown"
            break
        new = clipped * np.sqrt(cfg.k) / norm
        move = float(np.sqrt(((new - f) ** 2).sum() / cfg.k))
        f = new
        resid = f @ f.sum(0) - 1
        if cfg.ascend and move < cfg.tol_dual:
            dual = dual + w * resid
        feas = float(np.sqrt((resid**2).sum() / n))
        trace.append({"iter": t, "move": move, "feas": feas})
        if move < min(cfg.tol_dual, cfg.tol_conv) and feas < cfg.tol_conv and t >= cfg.min_iter:
            status = "converged"
            break
    return Fit(f, dual, trace, status, time.perf_counter() - began, True)


def too_many(points: DataFrame, limit: int | None = None) -> bool:
    """Whether one worker may not hold the points."""
    shape = points.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("x")).alias("d")).first()
    return shape.n * (shape.d or 0) * 8 > (LOCAL_LIMIT if limit is None else limit)


def local_points(points: DataFrame, limit: int = LOCAL_LIMIT) -> pd.DataFrame:
    """The points in id order, after a check that they are few enough for one worker."""
    shape = points.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("x")).alias("d")).first()
    if shape.n * (shape.d or 0) * 8 > limit:
        raise ValueError(f"{shape.n} x {shape.d} points are too many for local fits; use fit_distributed")
    return points.orderBy("id").toPandas()


def a_run_a_task(spark: SparkSession, grid: Sequence[dict]) -> DataFrame:
    """(run_id, spec) with each run in a task of its own; runs that take longest are first, so none of them is left for the end."""
    longest = sorted(enumerate(grid), key=lambda g: (g[1]["method"] not in ("nfk", "plain_nfk"), -g[1].get("n", 0), -(g[1].get("max_iter") or 0)))
    rows = spark.sparkContext.parallelize([(i, json.dumps(g)) for i, g in longest], max(1, len(grid)))
    return spark.createDataFrame(rows, "run_id long, spec string")


MIXTURE_SCHEMA = "run_id long, method string, seed int, n long, d int, k int, rank int, gamma double, cap int, iters int, feas double, move double, wcss double, loop_seconds double, total_seconds double, status string, ari double, nmi double, error double"


def fit_mixtures(spark: SparkSession, grid: Sequence[dict], limit: int = LOCAL_LIMIT) -> DataFrame:
    """Scored runs on planted mixtures that each task makes for itself: a new data set a seed, the same for all methods.

    A grid row has method, n, d, k, gamma, seed and what the method takes. The loop's seconds are those of the
    iterations (of a Lloyd run, all); the total has the data's preparation and the labels too.
    """
    from factorclust.operators import methods, metrics
    from factorclust.sources.points import mixture_rows

    if any(g["n"] * g["d"] * 8 > limit for g in grid):
        raise ValueError("a mixture is too large for one task; use resident.fit on sources.points.mixture")
    runs = a_run_a_task(spark, grid)
    factors = sum(g["method"] == "nfk" for g in grid)
    threads = spark.sparkContext.defaultParallelism // max(1, factors)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for run_id, spec in zip(b.run_id, map(json.loads, b.spec), strict=True):
                ids = np.arange(spec["n"])
                x, truth = mixture_rows(ids, spec["n"], spec["d"], spec["k"], spec["gamma"], spec["seed"])
                began = time.perf_counter()
                rows = methods.run(run_id, {**spec, "threads": threads}, ids, x, truth)
                total = time.perf_counter() - began
                yield pd.DataFrame([{
                    **{c: r[c] for c in ("run_id", "method", "seed", "rank", "cap", "iters", "feas", "move", "wcss", "status")}, **{c: spec[c] for c in ("n", "d", "k", "gamma")},
                    "loop_seconds": r["seconds"], "total_seconds": total, **{c: v for c, v in metrics.scores_np(np.asarray(r["labels"]), truth).items() if c != "purity"},
                } for r in rows])[[c.split()[0] for c in MIXTURE_SCHEMA.split(", ")]]

    return runs.mapInPandas(run, MIXTURE_SCHEMA)


RUN_SCHEMA = "run_id long, id long, cluster int"
RESULT_SCHEMA = "run_id long, method string, seed int, rank int, cap int, iters int, feas double, move double, objective double, wcss double, seconds double, status string, bound_ok boolean, labels array<int>"


def fit_grouped(points: DataFrame, grid: Sequence[dict], limit: int = LOCAL_LIMIT) -> DataFrame:
    """One row a run (and cap): each run of the grid is a local loop in a task of its own.

    The points are broadcast, below ``limit`` bytes; a grid row has method, seed and what the method takes.
    """
    from factorclust.operators import methods

    spark = points.sparkSession
    pdf = local_points(points, limit)
    x = np.stack(pdf.x.to_numpy()) if len(pdf) else np.zeros((0, 1))
    held = spark.sparkContext.broadcast((pdf.id.to_numpy(), x, pdf.truth.to_numpy() if "truth" in pdf else None))
    runs = a_run_a_task(spark, grid)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, x, truth = held.value
        for b in batches:
            for run_id, spec in zip(b.run_id, b.spec, strict=True):
                yield pd.DataFrame(methods.run(run_id, json.loads(spec), ids, x, truth))

    return runs.mapInPandas(run, RESULT_SCHEMA)


def labels_of_runs(points: DataFrame, runs: DataFrame) -> DataFrame:
    """(run_id, cap, id, cluster) of grouped runs; labels come in the order of ids."""
    ids = points.select("id").orderBy("id").agg(F.array_sort(F.collect_list("id")).alias("ids"))  # as bounded as the points of a grouped fit
    return runs.join(F.broadcast(ids)).select("run_id", "cap", F.explode(F.arrays_zip("ids", "labels")).alias("e")).select("run_id", "cap", F.col("e.ids").alias("id"), F.col("e.labels").alias("cluster"))


# --- distributed ------------------------------------------------------------------------------------------------

def matrix(buffer: pa.Buffer | bytes, rows: int, width: int) -> np.ndarray:
    """Rows of a tile as they are kept, in 32 or 64 bits."""
    size = buffer.size if isinstance(buffer, pa.Buffer) else len(buffer)
    return np.frombuffer(buffer, np.float32 if size == 4 * rows * width else np.float64).reshape(rows, width)


STATE = "tile long, rows int, ids binary, z binary, raw binary, dual binary, sums array<double>"


@dataclass
class Model:
    """What is left of a distributed fit: the state table's path or frame, and the driver's small state."""

    state: DataFrame
    control_scale: float
    gram: np.ndarray
    trace: list[dict]
    status: str
    cfg: Config
    mean: np.ndarray
    sigma: float
    bound_ok: bool = True
    peaks: list[int] = field(default_factory=list)  # traced bytes of each task, where asked for
    tasks: int = 0

    def factor(self) -> DataFrame:
        """(id, f) rows of the factor."""
        scale, r = self.control_scale, self.cfg.r

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for ids, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    f = matrix(raw, len(ids) // 8, r).astype(np.float64) * scale
                    yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(ids, np.int64)), pa.ListArray.from_arrays(pa.array(np.arange(len(f) + 1) * r, pa.int32()), pa.array(f.ravel()))], names=["id", "f"])

        return self.state.select("ids", "raw").mapInArrow(run, "id long, f array<double>")

    def labels(self) -> DataFrame:
        """(id, cluster): columns are grouped on the driver's Gram matrix, rows labelled where they lie."""
        groups = rounding.column_groups(self.gram, self.cfg.k)
        return self.factor().select("id", rounding.label_column(F.col("f"), groups).alias("cluster"))

    def wcss(self, shot: int | None = None) -> float:
        """The within sum of squares of the points by their labels, or by those kept of an iteration, from K rows of sums a task."""
        groups, k, dtype = rounding.column_groups(self.gram, self.cfg.k), self.cfg.k, self.cfg.dtype

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for i in range(b.num_rows):
                    n, kept = b.column(0)[i].as_py(), b.column(2)[i].as_buffer()
                    z = np.frombuffer(b.column(1)[i].as_buffer(), dtype).reshape(n, -1).astype(np.float64)
                    labels = rounding.labels_of(np.frombuffer(kept, dtype).reshape(n, -1).astype(np.float64), groups) if shot is None else np.frombuffer(kept, np.int32)
                    sums = np.zeros((k, z.shape[1] + 2))
                    sums[:, 0] = np.bincount(labels, minlength=k)
                    sums[:, 1] = np.bincount(labels, weights=(z * z).sum(1), minlength=k)
                    for j in range(z.shape[1]):
                        sums[:, j + 2] = np.bincount(labels, weights=z[:, j], minlength=k)
                    yield pa.RecordBatch.from_pydict({"cluster": np.arange(k), "sums": [s.tolist() for s in sums]})

        rows = self.state.select("rows", "z", "raw" if shot is None else F.col("shots")[shot]).mapInArrow(run, "cluster long, sums array<double>").select("cluster", F.posexplode("sums").alias("at", "v"))
        total = {(x.cluster, x["at"]): x.v for x in rows.groupBy("cluster", "at").agg(F.sum("v").alias("v")).collect()}  # K x (d + 2) rows
        width = max((at for _, at in total), default=1) + 1
        t = np.array([[total.get((c, at), 0.0) for at in range(width)] for c in range(k)])
        return float(self.sigma**2 * (t[:, 1].sum() - ((t[:, 2:] ** 2).sum(1) / np.maximum(1, t[:, 0])).sum()))

    def feasibility(self) -> float:
        """The residual's root mean square, row by row."""
        colsum = F.array(*[F.lit(float(v)) for v in self._colsum()])
        from factorclust.functions.vectors import dot

        return float(self.factor().agg(F.sqrt(F.avg(F.pow(dot(F.col("f"), colsum) - 1, 2)))).first()[0])

    def _colsum(self) -> np.ndarray:
        rows = self.factor().select(F.posexplode("f").alias("j", "v")).groupBy("j").agg(F.sum("v").alias("s")).collect()  # r rows
        out = np.zeros(self.cfg.r)
        for row in rows:
            out[row.j] = row.s
        return out

    def save(self, path: str) -> None:
        self.state.select("tile", "rows", "ids", "z", "raw", "dual").write.mode("overwrite").parquet(f"{path}/state")
        spark = self.state.sparkSession
        small = json.dumps({"scale": self.control_scale, "gram": self.gram.tolist(), "trace": self.trace, "status": self.status, "cfg": asdict(self.cfg), "mean": self.mean.tolist(), "sigma": self.sigma})
        spark.createDataFrame([(small,)], "model string").coalesce(1).write.mode("overwrite").json(f"{path}/driver")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Model:
        small = json.loads(spark.read.schema("model string").json(f"{path}/driver").first().model)
        cfg = Config(**small["cfg"])
        state = spark.read.parquet(f"{path}/state").withColumn("sums", F.lit(None).cast("array<double>"))
        return Model(state, small["scale"], np.array(small["gram"]), small["trace"], small["status"], cfg, np.array(small["mean"]), small["sigma"])


def build_tiles(points: DataFrame, mean: np.ndarray, sigma: float, cfg: Config, tile_rows: int = TILE_ROWS, partitions: int | None = None) -> DataFrame:
    """The first state: normalised rows and the initial factor of each tile, with their sums."""
    if partitions:
        points = points.repartition(partitions, "id")
    r = cfg.r
    m, s = (mean, sigma) if cfg.normalise else (np.zeros_like(mean), 1.0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        serial = itertools.count(TaskContext.get().partitionId() << 32)
        for b in batches:
            for at in range(0, b.num_rows, tile_rows):
                part = b.slice(at, tile_rows)
                ids = part.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                z = ((part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) - m) / s).astype(cfg.dtype)
                raw, dual = init.raw_factor(ids, r, cfg.seed, cfg.init).astype(cfg.dtype), np.zeros(len(ids))
                yield _row(next(serial), ids.tobytes(), z, raw, dual, sums_of(z.astype(np.float64), *[raw.astype(np.float64)] * 2, dual))

    return points.select("id", "x").mapInArrow(run, STATE)


def _row(tile: int, ids: bytes, z: np.ndarray, raw: np.ndarray, dual: np.ndarray, s: Sums) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array([tile], pa.int64()), pa.array([len(raw)], pa.int32()), pa.array([ids], pa.binary()), pa.array([z.tobytes()], pa.binary()), pa.array([raw.tobytes()], pa.binary()), pa.array([dual.tobytes()], pa.binary()), pa.array([s.pack().tolist()], pa.list_(pa.float64()))],
        names=["tile", "rows", "ids", "z", "raw", "dual", "sums"],
    )


def sweep(state: DataFrame, control: Control, d: int, r: int) -> DataFrame:
    """The next state; the control goes out as a broadcast of d x r numbers and some more."""
    held = state.sparkSession.sparkContext.broadcast(control)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = held.value
        for b in batches:
            for i in range(b.num_rows):
                dual = np.frombuffer(b.column(5)[i].as_buffer())
                z, raw = (matrix(b.column(k)[i].as_buffer(), len(dual), w) for k, w in ((3, d), (4, r)))
                new, dual, s = fused_step(z, raw, dual, c)
                yield _row(b.column(0)[i].as_py(), b.column(2)[i].as_py(), z, new, dual, s)

    return state.mapInArrow(run, STATE)


def add_up(state: DataFrame, d: int, r: int, tiles: int | None = None) -> Sums:
    """The sums over all tiles: d r + r^2 + 2 r + 5 numbers reach the driver, or, of FEW tiles, as many from each (no shuffle)."""
    if tiles is not None and tiles <= FEW:
        return Sums.unpack(np.sum([x.sums for x in state.select("sums").collect()], axis=0), d, r)
    rows = state.select(F.posexplode("sums").alias("at", "v")).groupBy("at").agg(F.sum("v").alias("v")).collect()
    v = np.zeros(d * r + r + r * r + r + 5)
    for row in rows:
        v[row["at"]] = row.v
    return Sums.unpack(v, d, r)


def _cut(state: DataFrame, folder: str) -> tuple[DataFrame, str]:
    path = f"{folder}/{uuid.uuid4().hex}"
    state.write.parquet(path)
    return state.sparkSession.read.parquet(path), path


def _delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


_own: dict[str, str] = {}


def state_folder(spark: SparkSession) -> str:
    """Where states are cut to: below spark.checkpoint.dir, or a folder of our own where that is unset on one machine (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        app = spark.sparkContext.applicationId
        if app not in _own:
            folder = tempfile.mkdtemp(prefix="factorclust-")
            atexit.register(shutil.rmtree, folder, True)
            _own[app] = f"file://{folder}"
        root = _own[app]
    return f"{root.rstrip('/')}/factorclust-states"


def fit_distributed(points: DataFrame, cfg: Config, tile_rows: int = TILE_ROWS, partitions: int | None = None, cut_every: int = 10, level: StorageLevel = StorageLevel.MEMORY_AND_DISK, resume: Model | None = None) -> Model:
    """One job an iteration. ``resume`` goes on from a saved model, with its state, dual and trace."""
    spark = points.sparkSession
    folder = state_folder(spark)
    stats = column_stats(points)
    n, d, mean = stats["n"], stats["d"], stats["mean"]
    if not 1 <= cfg.k <= n:
        raise ValueError(f"{cfg.k} clusters of {n} points")
    sigma = float(np.sqrt(np.linalg.eigvalsh(gram_matrix(points, mean))[-1])) if cfg.normalise else 1.0
    if cfg.normalise and not sigma > 1e-150:
        raise ValueError("all points are equal")
    driver = Driver(cfg, n, d)
    if resume is None:
        state, path = _cut(build_tiles(points, mean, sigma, cfg, tile_rows, partitions), folder)
        tiles = state.count()
        control: Control | None = driver.first(add_up(state, d, cfg.r, tiles))
    else:
        driver.trace = list(resume.trace)
        driver.dual_updates = resume.trace[-1]["dual_updates"] if resume.trace else 0
        state, control, path, tiles = resume.state, _control_of(resume, driver, d), None, None
    scale, cached = control.scale, None
    while control is not None:
        began = time.perf_counter()
        new = sweep(state, control, d, cfg.r)
        t = len(driver.trace) + 1
        new, new_path = _cut(new, folder) if t % cut_every == 0 else (new.persist(level), None)
        s = add_up(new, d, cfg.r, tiles)
        nxt = driver.advance(s, time.perf_counter() - began)
        if driver.status == "breakdown":
            break
        if cached is not None:
            cached.unpersist()
        cached = None if new_path else new
        if new_path:  # nothing reads the cut before it any more
            if path:
                _delete(spark, path)
            path = new_path
        state, scale, control = new, driver.scale, nxt
    return Model(state, scale, driver.gram, driver.trace, driver.status, cfg, mean, sigma, driver.bound_ok)


def _control_of(model: Model, driver: Driver, d: int) -> Control:
    """The control that a saved state continues with; a dual step that was due is done from its rows."""
    r, scale = model.cfg.r, model.control_scale

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                dual = np.frombuffer(b.column(2)[i].as_buffer())
                z, raw = (matrix(b.column(k)[i].as_buffer(), len(dual), w).astype(np.float64) for k, w in ((0, d), (1, r)))
                s = sums_of(z, raw, raw, dual)
                yield pa.RecordBatch.from_arrays([pa.array([s.pack().tolist()], pa.list_(pa.float64()))], names=["sums"])

    s = add_up(model.state.select("z", "raw", "dual").mapInArrow(run, "sums array<double>"), d, r)
    last = model.trace[-1]
    return driver._control(s, scale, fire=model.cfg.ascend and last["move"] < model.cfg.tol_dual)


def with_seed(cfg: Config, seed: int) -> Config:
    return replace(cfg, seed=seed)
