"""The arithmetic of one tile: the fused factor step, nearest centroids, and small dense helpers.

A tile holds rows of points ``z`` and of the unscaled factor ``raw``, with the dual of each row. The step
reads what the driver knows (Control) and gives, in one sweep, the next unscaled factor and every sum that
the driver needs to know for the step after it; no gradient and no second factor is kept.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Norm of the update at or below which normalisation breaks down.
BREAKDOWN = 1e-20
#: Rows that a step in memory takes at once: they and what is made of them stay in a core's cache.
STEP_ROWS = 512
#: The step times K and the penalty, where none is given. Chosen without labels, as the largest of 0.3, 0.5 and 0.8 (with
#: dual tolerances from 1e-3 to 3e-2) at which runs of K = 10 and 20 on mixtures and planted tables met the stop rule.
STEP = 0.8


@dataclass(frozen=True)
class Config:
    """Parameters of a fit. ``step`` may be a number, None (STEP / (K penalty)) or "bound" (theta over the smoothness bound).

    ``storage`` "single" keeps points and factor as 32-bit numbers; steps and sums are made in 64 bits all the same.
    """

    k: int
    rank: int | None = None
    step: float | str | None = None
    penalty: float = 1.0
    tol_dual: float = 3e-2
    tol_conv: float = 1e-3
    min_iter: int = 10
    max_iter: int = 3000
    ascend: bool = True
    normalise: bool = True
    round_scale: bool = False
    theta: float = 0.9
    init: str = "uniform"
    seed: int = 0
    storage: str = "double"

    @property
    def fixed_step(self) -> float:
        return STEP / (self.k * self.penalty) if self.step is None else float(self.step)

    @property
    def dtype(self) -> np.dtype:
        return np.dtype({"double": np.float64, "single": np.float32}[self.storage])

    @property
    def r(self) -> int:
        r = 2 * self.k if self.rank is None else self.rank
        if r < self.k:
            raise ValueError(f"rank {r} is below the number of clusters {self.k}")
        return r


@dataclass
class Sums:
    """What a sweep reports, summed over tiles."""

    pull: np.ndarray  # d x r
    colsum: np.ndarray
    gram: np.ndarray  # r x r
    dual_colsum: np.ndarray  # factor times dual
    nn: float
    oo: float
    no: float
    dual: float
    dual2: float

    def pack(self) -> np.ndarray:
        return np.concatenate([self.pull.ravel(), self.colsum, self.gram.ravel(), self.dual_colsum, [self.nn, self.oo, self.no, self.dual, self.dual2]])

    @staticmethod
    def unpack(v: np.ndarray, d: int, r: int) -> Sums:
        cuts = np.cumsum([d * r, r, r * r, r])
        pull, colsum, gram, dv, tail = np.split(v, cuts)
        return Sums(pull.reshape(d, r), colsum, gram.reshape(r, r), dv, *map(float, tail))


@dataclass
class Control:
    """What the driver tells the tiles: the factor is scale * raw; ``fire`` asks for the pending dual step."""

    scale: float
    pull: np.ndarray
    colsum: np.ndarray
    shift: np.ndarray
    weight: float
    step: float
    fire: bool


def sums_of(z: np.ndarray, new: np.ndarray, old: np.ndarray, dual: np.ndarray) -> Sums:
    return Sums(z.T @ new, new.sum(0), new.T @ new, new.T @ dual, float((new * new).sum()), float((old * old).sum()), float((new * old).sum()), float(dual.sum()), float((dual * dual).sum()))


def fused_step(z: np.ndarray, raw: np.ndarray, dual: np.ndarray, c: Control) -> tuple[np.ndarray, np.ndarray, Sums]:
    z = z.astype(np.float64, copy=False)
    f = raw.astype(np.float64, copy=False) * c.scale
    resid = f @ c.colsum - 1
    if c.fire:
        dual = dual + c.weight * resid
    eff = dual + c.weight * resid
    new = z @ c.pull
    new *= 2 * c.step
    new += f
    new -= c.step * np.outer(eff, c.colsum)
    new -= c.step * c.shift
    np.maximum(new, 0, out=new)
    new = new.astype(raw.dtype, copy=False)  # the sums are those of what is kept
    return new, dual, sums_of(z, new.astype(np.float64, copy=False), f, dual)


def step_rows(z: np.ndarray, raw: np.ndarray, dual: np.ndarray, c: Control, out: np.ndarray | None = None) -> Sums:
    """The fused step by STEP_ROWS rows at a time: the next factor goes to ``out``, or over ``raw``, the next dual over ``dual``."""
    out = raw if out is None else out
    if z.dtype != np.float64 or raw.dtype != np.float64:
        out[:], dual[:], s = fused_step(z, raw, dual, c)
        return s
    r, most = raw.shape[1], min(STEP_ROWS, max(1, len(raw)))
    pull, ends = 2 * c.step * c.pull, np.stack([c.step * c.colsum, c.step * c.shift])
    held, less, eff, kept = np.empty((most, r)), np.empty((most, r)), np.ones((most, 2)), np.ones((most, 2))
    total = Sums(np.zeros_like(pull), np.zeros(r), np.zeros((r, r)), np.zeros(r), 0.0, 0.0, 0.0, 0.0, 0.0)
    sides, pulled, squared = np.zeros((2, r)), np.empty_like(pull), np.empty((r, r))
    for at in range(0, len(raw), most):
        x, old, y, new = (a[at : at + most] for a in (z, raw, dual, out))
        m = len(x)
        f = np.multiply(old, c.scale, out=held[:m])
        resid = f @ c.colsum
        resid -= 1
        resid *= c.weight
        if c.fire:
            y += resid
        eff[:m, 0] = y + resid
        kept[:m, 0] = y
        np.matmul(x, pull, out=new)
        new += f
        new -= np.matmul(eff[:m], ends, out=less[:m])
        np.maximum(new, 0, out=new)
        total.pull += np.matmul(x.T, new, out=pulled)
        total.gram += np.matmul(new.T, new, out=squared)
        sides += kept[:m].T @ new
        total.oo += float(np.vdot(f, f))
        total.no += float(np.vdot(f, new))
        total.dual += float(y.sum())
        total.dual2 += float(np.vdot(y, y))
    total.dual_colsum, total.colsum, total.nn = sides[0], sides[1], float(np.trace(total.gram))
    return total


class Driver:
    """Turns the sums of a sweep into the control of the next: scaling, movement, feasibility, dual step, stop."""

    def __init__(self, cfg: Config, n: int, d: int):
        self.cfg, self.n, self.d = cfg, n, d
        self.weight = cfg.penalty / (n if cfg.normalise else 1)
        self.trace: list[dict] = []
        self.dual_updates, self.dual_norm, self.status = 0, 0.0, "running"
        self.bound_ok = True

    def _step(self) -> float:
        c = self.cfg
        bound = 2 + 2 * self.dual_norm + c.penalty * (6 * c.k + 2)
        step = c.theta / bound if c.step == "bound" else c.fixed_step
        self.bound_ok = step < 1 / bound
        return step

    def first(self, s: Sums) -> Control:
        """The control of the first step, from the sums of the initial factor (its squared norm becomes K)."""
        return self._control(s, np.sqrt(self.cfg.k / s.nn), fire=False)

    def _control(self, s: Sums, scale: float, fire: bool) -> Control:
        colsum, gram = s.colsum * scale, s.gram * scale**2
        lift = gram @ colsum - colsum  # factor times residual
        projected = s.dual_colsum * scale
        self.feas2 = max(0.0, float(colsum @ gram @ colsum - 2 * colsum @ colsum + self.n))
        if fire:
            # |dual + w resid|^2, from the sums
            dual_resid = float(projected @ colsum) - s.dual
            self.dual_norm = float(np.sqrt(max(0.0, s.dual2 + 2 * self.weight * dual_resid + self.weight**2 * self.feas2) * self.n))
            projected = projected + self.weight * lift
            self.dual_updates += 1
        self.gram, self.scale = gram, scale
        return Control(scale, s.pull * scale, colsum, projected + self.weight * lift, self.weight, self._step(), fire)

    def advance(self, s: Sums, seconds: float = 0.0) -> Control | None:
        """The next control, or None at the end (``status`` says why)."""
        cfg = self.cfg
        if np.sqrt(s.nn) <= BREAKDOWN:
            self.status = "breakdown"
            return None
        scale = np.sqrt(cfg.k / s.nn)
        if cfg.round_scale:
            scale = float(np.float32(scale))
        move = float(np.sqrt(max(scale**2 * s.nn + s.oo - 2 * scale * s.no, 0.0) / cfg.k))
        fire = cfg.ascend and move < cfg.tol_dual
        control = self._control(s, scale, fire)
        feas = float(np.sqrt(self.feas2 / self.n))
        t = len(self.trace) + 1
        self.trace.append({"iter": t, "move": move, "feas": feas, "nn": s.nn, "oo": s.oo, "no": s.no, "scale": float(scale), "objective": -float((control.pull**2).sum()), "dual_updates": self.dual_updates, "seconds": seconds})
        if move < min(cfg.tol_dual, cfg.tol_conv) and feas < cfg.tol_conv and t >= cfg.min_iter:
            self.status = "converged"
            return None
        if t >= cfg.max_iter:
            self.status = "capped"
            return None
        return control


def nearest(x: np.ndarray, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nearest centroid, squared distance) of each row; ties go to the lowest index."""
    best, far = np.empty(len(x), np.int64), np.empty(len(x))
    norms = (centroids * centroids).sum(1)[None, :]
    for at in range(0, len(x), STEP_ROWS):
        rows = x[at : at + STEP_ROWS]
        dist = (rows * rows).sum(1)[:, None] + norms
        cross = rows @ centroids.T
        cross *= 2
        dist -= cross
        chosen = np.argmin(np.round(dist, 12), axis=1)
        best[at : at + STEP_ROWS], far[at : at + STEP_ROWS] = chosen, dist[np.arange(len(rows)), chosen]
    return best, np.maximum(far, 0, out=far)


def spectral_norm(x: np.ndarray) -> float:
    """The largest singular value of rows that are already centred."""
    s = float(np.sqrt(max(np.linalg.eigvalsh(x.T @ x)[-1], 0.0)))
    if s <= 1e-150:
        raise ValueError("all points are equal")
    return s
