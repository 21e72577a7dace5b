"""The distributed fit whose points and factor stay in the tasks that hold them, for as many tasks as run at once.

One barrier stage runs the whole loop: each task builds its tiles once and steps them in place. The tasks' sums,
d r + r^2 + 2 r + 5 numbers a task and iteration, are added up by the first task and sent back, over sockets whose
place and password go round by the stage's all-gather (which itself takes a second a call, too long for each
iteration). Each task turns the same sums into the same control, so nothing waits for the driver, and neither points
nor factor are written, moved or copied between iterations: one factor-sized buffer and a tile's temporaries. All
sums pass through one task, so TASKS bounds their number; what doesn't fit into that many workers is for ``solver``
(a job an iteration) or ``paired`` (points and state in tables).

Every ``save_every`` iterations the tasks write their factors to the shared folder. A lost executor ends the
stage, Spark runs it again, and its tasks go on from the last snapshot that all of them had finished.

An update that clamps to zero everywhere ends the fit with the status "breakdown" and a factor of zeros.

``lloyd_fit`` runs Lloyd's whole loop in such a stage; a lost executor starts it again.
"""

from __future__ import annotations

import json
import math
import pickle
import secrets
import socket
import tempfile
import time
import tracemalloc
import uuid
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.operators import init, lloyd, rounding
from factorclust.operators.kernel import STEP_ROWS, Config, Control, Driver, Sums, nearest, step_rows, sums_of
from factorclust.operators.normalize import column_stats, gram_matrix
from factorclust.operators.solver import TILE_ROWS, Model, _cut, _delete, state_folder

#: Tasks of a stage; bytes of points and factor that each may hold.
TASKS, TASK_LIMIT = 64, 2 << 30
#: Rows that are worth a task.
LEAST = 2_048
#: Bytes of points that a task of a Lloyd run keeps in memory, where it may; those beyond them lie in a file of its own.
KEPT = 256 << 20
#: Seconds that a task waits for the others before it fails, and with it the stage, which then runs again.
PATIENCE = 600.0
STATE = "tile long, rows int, ids binary, z binary, raw binary, dual binary, shots map<int,binary>, report string"


def tasks_for(points: DataFrame, n: int, bytes_a_row: int) -> int:
    """As many tasks as cores and TASKS allow, of LEAST rows at least; raises where they could not hold the rows."""
    cores = min(TASKS, points.sparkSession.sparkContext.defaultParallelism)
    if n * bytes_a_row > cores * TASK_LIMIT:
        raise ValueError(f"{n} rows of {bytes_a_row} bytes are too many for {cores} tasks; use solver.fit_distributed or paired.fit")
    return max(1, min(cores, math.ceil(n / LEAST)))


class Adder:
    """Adds up arrays of one size over the tasks of a barrier stage; in the order of the tasks, so all have equal sums."""

    def __init__(self, here, size: int, patience: float = PATIENCE):
        part, many = here.partitionId(), len(here.getTaskInfos())
        self.size, self.to, self.of = size, None, []
        server = None
        if part == 0:
            server = socket.create_server(("", 0), backlog=many)
            server.settimeout(patience)
            said = json.dumps([here.getTaskInfos()[0].address.rsplit(":", 1)[0], server.getsockname()[1], secrets.token_hex(16)])
        place, port, password = json.loads(here.allGather(said if part == 0 else "")[0])
        if part == 0:
            found: dict[int, socket.socket] = {}
            while len(found) < many - 1:
                s, _ = server.accept()
                s.settimeout(patience)
                hello = _read(s, 36).decode("ascii", "replace")
                if hello[:32] == password:
                    found[int(hello[32:])] = s
                else:
                    s.close()
            server.close()
            self.of = [found[k] for k in sorted(found)]
        else:
            self.to = socket.create_connection((place, port), patience)
            self.to.sendall(f"{password}{part:04d}".encode())
        for s in [*self.of, *([self.to] if self.to else [])]:
            s.setsockopt(socket.IPPROTO_TCP, socket.TCP_NODELAY, 1)

    def __call__(self, mine: np.ndarray) -> np.ndarray:
        if self.to:
            self.to.sendall(mine.tobytes())
            return np.frombuffer(_read(self.to, 8 * self.size))
        total = mine.copy()
        for s in self.of:
            total += np.frombuffer(_read(s, 8 * self.size))
        for s in self.of:
            s.sendall(total.tobytes())
        return total

    def close(self) -> None:
        for s in [*self.of, *([self.to] if self.to else [])]:
            s.close()


def _read(s: socket.socket, n: int) -> bytes:
    out = bytearray()
    while len(out) < n:
        part = s.recv(min(n - len(out), 1 << 20))
        if not part:
            raise ConnectionError("a task of the stage is gone")
        out += part
    return bytes(out)


class Tile:
    def __init__(self, ids: np.ndarray, z: np.ndarray, cfg: Config):
        self.ids, self.z = ids, z.astype(cfg.dtype, copy=False)
        self.raw, self.dual = init.raw_factor(ids, cfg.r, cfg.seed, cfg.init).astype(cfg.dtype), np.zeros(len(ids))
        self.shots: dict[int, np.ndarray] = {}

    def sums(self) -> np.ndarray:
        f = self.raw.astype(np.float64, copy=False)
        return sums_of(self.z.astype(np.float64, copy=False), f, f, self.dual).pack()


def fused(tiles: list[Tile], c: Control) -> np.ndarray:
    """One step of all tiles, each factor overwritten by the next; the sums."""
    total: np.ndarray | float = 0.0
    for t in tiles:
        total = total + step_rows(t.z, t.raw, t.dual, c).pack()
    return total


def three_buffers(tiles: list[Tile], c: Control) -> np.ndarray:
    """The same step with the gradients of all tiles, then their second factors, kept whole beside the first."""
    gradients, factors, total = [], [], 0.0
    for t in tiles:
        f = t.raw * c.scale
        resid = f @ c.colsum - 1
        if c.fire:
            t.dual = t.dual + c.weight * resid
        gradients.append(np.outer(t.dual + c.weight * resid, c.colsum) + c.shift - 2 * t.z @ c.pull)
    for t, g in zip(tiles, gradients, strict=True):
        factors.append(np.maximum(t.raw * c.scale - c.step * g, 0))
    for t, new in zip(tiles, factors, strict=True):
        total = total + sums_of(t.z, new, t.raw * c.scale, t.dual).pack()
        t.raw = new
    return total


def fit(points: DataFrame, cfg: Config, tasks: int | None = None, tile_rows: int = TILE_ROWS, save_every: int = 200, buffers: int = 1, trace_memory: bool = False, caps: Sequence[int] = ()) -> Model:
    """As solver.fit_distributed, with the same iterates up to rounding. ``buffers`` is 1 (fused) or 3.

    ``caps`` asks for labels at those iterations too: a map of them beside the rows, of those that come before the end.
    """
    spark = points.sparkSession
    stats = column_stats(points)
    n, d, mean = stats["n"], stats["d"], stats["mean"]
    if not 1 <= cfg.k <= n:
        raise ValueError(f"{cfg.k} clusters of {n} points")
    sigma = float(np.sqrt(np.linalg.eigvalsh(gram_matrix(points, mean))[-1])) if cfg.normalise else 1.0
    if cfg.normalise and not sigma > 1e-150:
        raise ValueError("all points are equal")
    tasks = tasks or tasks_for(points, n, 8 * (d + 2 * cfg.r + 4))
    folder = state_folder(spark)
    snapshots = f"{folder}/snapshots-{uuid.uuid4().hex}"
    m, s = (mean, sigma) if cfg.normalise else (np.zeros_like(mean), 1.0)
    held = spark.sparkContext.broadcast((cfg, m, s))
    step = {1: fused, 3: three_buffers}[buffers]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import BarrierTaskContext

        cfg, m, s = held.value
        here = BarrierTaskContext.get()
        part = here.partitionId()
        if trace_memory:
            tracemalloc.start()
        tiles: list[Tile] = []
        for b in batches:
            for at in range(0, b.num_rows, tile_rows):
                x = b.slice(at, tile_rows)
                ids = x.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                tiles.append(Tile(ids, (x.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) - m) / s, cfg))

        add = Adder(here, (d + cfg.r + 2) * cfg.r + 5)

        def all_sums(mine: np.ndarray | float) -> Sums:
            return Sums.unpack(add(mine + np.zeros(add.size)), d, cfg.r)

        system, top = pafs.FileSystem.from_uri(snapshots)
        saved = _last(system, top)
        if saved is None:
            driver = Driver(cfg, n, d)
            control: Control | None = driver.first(all_sums(sum((t.sums() for t in tiles), 0.0)))
        else:
            with system.open_input_stream(f"{top}/{saved}/{part}") as f:
                driver, control, factors = pickle.load(f)
            by_first = {int(ids[0]): rest for ids, *rest in factors}
            for t in tiles:
                t.raw, t.dual, t.shots = by_first[int(t.ids[0])]
        scale = driver.scale
        if trace_memory:
            tracemalloc.reset_peak()
        while control is not None:
            began = time.perf_counter()
            control = driver.advance(all_sums(step(tiles, control)), time.perf_counter() - began)
            scale = scale if driver.status == "breakdown" else driver.scale
            if len(driver.trace) in caps and driver.status != "breakdown":
                groups = rounding.column_groups(driver.gram, cfg.k)
                for t in tiles:
                    t.shots[len(driver.trace)] = rounding.labels_of(t.raw.astype(np.float64, copy=False), groups).astype(np.int32)
            if control is not None and len(driver.trace) % save_every == 0:
                _save(system, top, len(driver.trace), here.partitionId(), add, (driver, control, [(t.ids, t.raw, t.dual, t.shots) for t in tiles]))
        add.close()
        # a report beside the first tile, of every task the same but for the bytes
        peak = tracemalloc.get_traced_memory()[1] if trace_memory else 0
        tracemalloc.stop()
        report = json.dumps({"scale": float(scale), "gram": driver.gram.tolist(), "trace": driver.trace, "status": driver.status, "bound_ok": driver.bound_ok, "peak": peak, "tasks": len(here.getTaskInfos())})
        for i, t in enumerate(tiles):
            yield pa.RecordBatch.from_arrays(
                [pa.array([(part << 32) + i], pa.int64()), pa.array([len(t.ids)], pa.int32()), *[pa.array([x.tobytes()], pa.binary()) for x in (t.ids, t.z, t.raw, t.dual)], pa.array([[(c, x.tobytes()) for c, x in t.shots.items()]], pa.map_(pa.int32(), pa.binary())), pa.array([report if i == 0 else None], pa.string())],
                names=["tile", "rows", "ids", "z", "raw", "dual", "shots", "report"],
            )

    spread = points.select("id", "x").repartition(tasks, "id").sortWithinPartitions("id")  # tiles are the same in a second run
    # Spark can run a barrier stage again if a shuffle follows it, not if it writes the result itself
    state, _ = _cut(spread.mapInArrow(run, STATE, barrier=True).repartition(tasks, "tile"), folder)
    _delete(spark, snapshots)
    reports = [json.loads(r.report) for r in state.where("report is not null").orderBy("tile").select("report").collect()]  # one a task
    first = reports[0]
    model = Model(state.drop("report"), first["scale"], np.array(first["gram"]), first["trace"], first["status"], cfg, mean, sigma, first["bound_ok"])
    model.peaks, model.tasks = [r["peak"] for r in reports], first["tasks"]
    return model


def labels_at(model: Model, cap: int) -> DataFrame:
    """(id, cluster) at an iteration that the fit was asked for and that came before its end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for ids, labels in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(ids, np.int64)), pa.array(np.frombuffer(labels, np.int32))], names=["id", "cluster"])

    return model.state.select("ids", F.col("shots")[cap].alias("labels")).mapInArrow(run, "id long, cluster int")


def replay(points: DataFrame, cfg: Config, forms: tuple[int, ...] = (1, 3), tile_rows: int = TILE_ROWS) -> dict[int, tuple[int, list[dict]]]:
    """(traced bytes of all partitions, trace) of the first ``cfg.max_iter`` steps with so many buffers, for points of any number.

    Nothing is kept between steps, moved or written: each step is a job whose tasks make their rows and their start anew and
    repeat the steps before it, by the controls that the driver has. A task holds one partition of the points, with all
    the buffers that the form needs for it; the sum of their peaks is what the form takes where all partitions are held.
    """
    d = len(points.select("x").first().x)

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d + 1, d + 1))
        for b in batches:
            x = np.column_stack([np.ones(b.num_rows), b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d)])
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array([total.ravel().tolist()], pa.list_(pa.float64()))], names=["sums"])

    def added(rows: DataFrame) -> np.ndarray:
        got = {x["at"]: x.v for x in rows.select(F.posexplode("sums").alias("at", "v")).groupBy("at").agg(F.sum("v").alias("v")).collect()}
        return np.array([got[at] for at in sorted(got)])

    t = added(points.select("x").mapInArrow(moments, "sums array<double>")).reshape(d + 1, d + 1)
    n, mean = int(round(t[0, 0])), t[0, 1:] / t[0, 0]
    sigma = float(np.sqrt(np.linalg.eigvalsh(t[1:, 1:] - n * np.outer(mean, mean))[-1]))
    size = (d + cfg.r + 2) * cfg.r + 5
    drivers = {f: Driver(cfg, n, d) for f in forms}
    controls: dict[int, list[Control]] = {f: [] for f in forms}
    peaks = dict.fromkeys(forms, 0)
    for at in range(cfg.max_iter + 1):
        held = points.sparkSession.sparkContext.broadcast((cfg, mean, sigma, controls))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            cfg, mean, sigma, controls = held.value
            tracemalloc.start()
            rows = []
            for b in batches:
                for at in range(0, b.num_rows, tile_rows):
                    x = b.slice(at, tile_rows)
                    rows.append((x.column(0).to_numpy(zero_copy_only=False).astype(np.int64), (x.column(1).flatten().to_numpy(zero_copy_only=False).reshape(x.num_rows, d) - mean) / sigma))
            out = []
            for form, before in controls.items():
                tiles = [Tile(ids, z, cfg) for ids, z in rows]
                total = sum((x.sums() for x in tiles), np.zeros(size)) if not before else 0.0
                tracemalloc.reset_peak()
                for c in before:
                    total = {1: fused, 3: three_buffers}[form](tiles, c)
                out += [*(total + np.zeros(size)).tolist(), float(tracemalloc.get_traced_memory()[1])]
                del tiles
            tracemalloc.stop()
            yield pa.RecordBatch.from_arrays([pa.array([out], pa.list_(pa.float64()))], names=["sums"])

        sums = added(points.select("id", "x").mapInArrow(run, "sums array<double>")).reshape(len(forms), size + 1)
        for form, s in zip(forms, sums, strict=True):
            driver, got = drivers[form], Sums.unpack(s[:-1], d, cfg.r)
            control = driver.advance(got) if at else driver.first(got)
            peaks[form] = max(peaks[form], int(s[-1])) if at else 0
            if control is not None:
                controls[form] = [*controls[form], control]
        if any(x.status != "running" for x in drivers.values()):
            break
    return {f: (peaks[f], drivers[f].trace) for f in forms}


class Rows:
    """The points of a task, for many passes: so many bytes of them in memory, the rest read anew in each pass from a file of the task's."""

    def __init__(self, limit: int):
        self.left, self.kept, self.file, self.shapes = limit, [], None, []

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        if x.nbytes <= self.left:
            self.kept.append((ids, x))
            self.left -= x.nbytes
            return
        self.file = self.file or tempfile.TemporaryFile(buffering=0)
        ids.tofile(self.file)
        x.tofile(self.file)
        self.shapes.append(x.shape)

    def __iter__(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        yield from self.kept
        if self.file:
            self.file.seek(0)
        for n, d in self.shapes:
            yield np.fromfile(self.file, np.int64, n), np.fromfile(self.file, np.float64, n * d).reshape(n, d)


def sweep_rows(rows: Rows, c: np.ndarray) -> np.ndarray:
    """K x d sums of the points nearest to each centroid, K sizes and the within sum of squares, in one array."""
    sums, sizes, within = np.zeros_like(c), np.zeros(len(c)), 0.0
    for _, block in rows:
        for at in range(0, len(block), STEP_ROWS):
            x = block[at : at + STEP_ROWS]
            labels, d2 = nearest(x, c)
            sums += (np.arange(len(c))[:, None] == labels).astype(np.float64) @ x
            sizes += np.bincount(labels, minlength=len(c))
            within += float(d2.sum())
    return np.concatenate([sums.ravel(), sizes, [within]])


def lloyd_fit(points: DataFrame, k: int, seed: int, stop: str = "norm", tol: float = lloyd.TOLERANCE, max_iter: int = lloyd.CAP, keep: bool = True, start: np.ndarray | None = None, tasks: int | None = None) -> tuple[DataFrame, np.ndarray, list[dict]]:
    """As lloyd.fit, with the same iterates up to rounding, from its seeds or from ``start``; the labels are written once.

    Without ``keep`` each sweep reads all points anew, block by block; with it a task keeps KEPT bytes of them in memory.
    """
    spark = points.sparkSession
    c = lloyd.seeds(points, k, seed) if start is None else start
    d = c.shape[1]
    tasks = tasks or max(1, min(TASKS, spark.sparkContext.defaultParallelism, math.ceil(points.count() / LEAST)))
    held = spark.sparkContext.broadcast((c, KEPT if keep else 0))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import BarrierTaskContext

        c, limit = held.value
        here = BarrierTaskContext.get()
        rows = Rows(limit)
        for b in batches:
            if b.num_rows:
                rows.add(b.column(0).to_numpy(zero_copy_only=False).astype(np.int64), b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d))
        add = Adder(here, k * (d + 1) + 1)
        trace, last = [], np.inf
        for it in range(1, max_iter + 1):
            began = time.perf_counter()
            total = add(sweep_rows(rows, c))
            sizes, within = total[k * d : -1], float(total[-1])
            new = lloyd.moved_to(c, total[: k * d].reshape(k, d), sizes)
            moved = lloyd.fall(last, within) if stop == "objective" else lloyd.movement(c, new, stop)
            trace.append({"iter": it, "moved": moved, "wcss": within, "empty": int((sizes == 0).sum()), "seconds": time.perf_counter() - began})
            c, last = new, within
            if moved <= tol:
                break
        add.close()
        if here.partitionId() == 0:  # a row of no point, with what all tasks know
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([None], pa.int32()), pa.array([None], pa.float64()), pa.array([json.dumps([c.tolist(), trace])])], names=["id", "cluster", "distance2", "report"])
        for ids, x in rows:
            labels, d2 = nearest(x, c)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(labels.astype(np.int32)), pa.array(d2), pa.nulls(len(ids), pa.string())], names=["id", "cluster", "distance2", "report"])

    spread = points.select("id", "x").repartition(tasks, "id").sortWithinPartitions("id")
    got, _ = _cut(spread.mapInArrow(run, "id long, cluster int, distance2 double, report string", barrier=True).repartition(tasks, "id"), state_folder(spark))
    c, trace = json.loads(got.where("report is not null").first().report)
    return got.where("report is null").select("id", "cluster", "distance2"), np.array(c), trace


def _last(system: pafs.FileSystem, top: str) -> str | None:
    """The last snapshot that every task had finished."""
    if system.get_file_info(top).type != pafs.FileType.Directory:
        return None
    done = [f.base_name for f in system.get_file_info(pafs.FileSelector(top)) if system.get_file_info(f"{f.path}/done").type == pafs.FileType.File]
    return max(done, key=int, default=None)


def _save(system: pafs.FileSystem, top: str, iteration: int, part: int, add: Adder, what: object) -> None:
    folder = f"{top}/{iteration}"
    system.create_dir(folder, recursive=True)
    with system.open_output_stream(f"{folder}/{part}") as f:
        pickle.dump(what, f)
    add(np.zeros(add.size))  # waits for all tasks' files, as the stage's barrier does, which takes a second
    if part == 0:
        with system.open_output_stream(f"{folder}/done") as f:
            f.write(b"")
        for old in system.get_file_info(pafs.FileSelector(top)):  # only the last one is read again
            if int(old.base_name) < iteration:
                system.delete_dir(old.path)
