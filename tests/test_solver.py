"""The solver: identities, equivalence of its forms, theory, recovery, edges."""

from __future__ import annotations

import math
import os

import numpy as np
import pandas as pd
import pytest

from factorclust.functions import theory
from factorclust.operators import checks, init, kernel, lloyd, metrics, resident, rounding, run_costs, solver
from factorclust.operators.kernel import Config
from factorclust.operators.relax import brute_force_partition, sdp_feasibility, sdp_objective, solve_sdp_small
from factorclust.sources.points import mixture, mixture_rows, planted


def points(n=120, k=3, d=5, far=6.0, seed=0):
    draw = np.random.default_rng(seed)
    truth = np.arange(n) % k
    c = np.eye(d)[:k] * far
    return c[truth] + draw.standard_normal((n, d)) * 0.5, truth


@pytest.fixture(scope="module")
def data(spark, small):
    return solver.local_points(planted(spark, small, 2.0))


def test_fused_and_three_buffer_iterates_agree():
    x, _ = points()
    cfg = Config(k=3, max_iter=80)
    a, b = solver.fit_local(x, cfg), solver.fit_threebuffer(x, cfg)
    assert np.abs(a.factor - b.factor).max() < 1e-10
    assert all(abs(s["feas"] - t["feas"]) < 1e-9 and abs(s["move"] - t["move"]) < 1e-9 for s, t in zip(a.trace, b.trace, strict=True))


def test_domain_is_kept_and_feasibility_matches_rows():
    x, _ = points()
    fit = solver.fit_local(x, Config(k=3, max_iter=200))
    f = fit.factor
    assert f.min() >= 0 and abs((f * f).sum() - 3) < 1e-9
    assert abs(np.sqrt(((f @ f.sum(0) - 1) ** 2).mean()) - fit.trace[-1]["feas"]) < 1e-7


def test_distributed_equals_local_on_any_tiling(spark):
    x, truth = points(300)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    cfg = Config(k=3, max_iter=25)
    local = solver.fit_local(x, cfg)
    for rows, parts in ((64, 3), (1000, 1)):
        far = solver.fit_distributed(df, cfg, tile_rows=rows, partitions=parts, cut_every=7)
        got = far.factor().orderBy("id").toPandas()
        assert np.abs(np.stack(got.f) - local.factor).max() < 1e-8
        assert abs(far.feasibility() - far.trace[-1]["feas"]) < 1e-7
    assert metrics.scores_np(far.labels().orderBy("id").toPandas().cluster.to_numpy(), truth)["ari"] > 0.9


@pytest.mark.parametrize("buffers", [1, 3])
def test_resident_equals_local_on_any_tiling(spark, buffers):
    x, truth = points(300)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    for storage, tol in (("double", 1e-8), ("single", 1e-5)):
        cfg = Config(k=3, max_iter=40, storage=storage)
        local = solver.fit_local(x, cfg)
        far = resident.fit(df, cfg, tasks=3, tile_rows=32, buffers=buffers)
        got = far.factor().orderBy("id").toPandas()
        assert np.abs(np.stack(got.f) - local.factor).max() < tol and far.tasks == 3 and len(far.trace) == len(local.trace)
    assert metrics.scores_np(far.labels().orderBy("id").toPandas().cluster.to_numpy(), truth)["ari"] > 0.9


LOSES_A_TASK = """
import os, sys
import numpy as np
from pyspark.sql import SparkSession
from factorclust.operators import resident, solver
from factorclust.operators.kernel import Config

spark = SparkSession.builder.master("local[2,4]").config("spark.ui.enabled", "false").getOrCreate()
x = np.random.default_rng(0).standard_normal((200, 5)) + 4 * np.eye(5)[np.arange(200) % 3]
real, seen, flag = resident.fused, {"n": 0}, sys.argv[1]

def dies_once(tiles, c):
    seen["n"] += 1
    if seen["n"] == 25 and not os.path.exists(flag):
        os.mkdir(flag)
        raise RuntimeError("lost")
    return real(tiles, c)

resident.fused = dies_once
df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
cfg = Config(k=3, max_iter=40, tol_conv=1e-9)
far, near = resident.fit(df, cfg, tasks=2, tile_rows=64, save_every=10), solver.fit_local(x, cfg)
apart = np.abs(np.stack(far.factor().orderBy("id").toPandas().f) - near.factor).max()
assert os.path.exists(flag) and len(far.trace) == 40 and apart < 1e-7, (len(far.trace), apart)
print("went on")
"""


def test_resident_goes_on_when_a_task_is_lost(tmp_path):
    import subprocess
    import sys

    done = subprocess.run([sys.executable, "-c", LOSES_A_TASK, str(tmp_path / "died")], capture_output=True, text=True, timeout=200)
    assert "went on" in done.stdout, done.stderr[-3000:]


def test_resident_refuses_what_its_tasks_cannot_hold(spark):
    with pytest.raises(ValueError, match="too many"):
        resident.tasks_for(spark.range(1), 10**10, 1000)


@pytest.mark.parametrize("seed", range(3))
def test_published_setting_is_recovered_where_lloyd_is_not(seed):
    """K = 20, d = 50, r = 30 at the threshold: the factor ends at the floor, single Lloyd runs mostly don't."""
    x, t = mixture_rows(np.arange(2000), 2000, 50, 20, 1.0, seed)
    fit = solver.fit_local(x, Config(k=20, rank=30, seed=seed, max_iter=6000))
    ours = metrics.scores_np(rounding.round_columns(fit.factor, 20), t)["ari"]
    floor = metrics.scores_np(kernel.nearest(x, np.stack([x[t == c].mean(0) for c in range(20)]))[0], t)["ari"]
    assert fit.status == "converged" and ours >= floor - 2e-3
    assert np.median([metrics.scores_np(lloyd.fit_local(x, 20, s).labels, t)["ari"] for s in range(6)]) < ours


def test_resume_goes_on_as_if_uninterrupted(spark, tmp_path):
    x, _ = points(200)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    half = solver.fit_distributed(df, Config(k=3, max_iter=12), tile_rows=80)
    half.save(str(tmp_path / "m"))
    back = solver.Model.load(spark, str(tmp_path / "m"))
    on = solver.fit_distributed(df, Config(k=3, max_iter=20), tile_rows=80, resume=back)
    once = solver.fit_local(x, Config(k=3, max_iter=20))
    got = on.factor().orderBy("id").toPandas()
    assert len(on.trace) == 20 and np.abs(np.stack(got.f) - once.factor).max() < 1e-8


def test_iteration_plan_has_no_shuffle_of_rows(spark):
    x, _ = points(100)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    cfg = Config(k=3)
    state = solver.build_tiles(df, x.mean(0), 1.0, cfg, tile_rows=50)
    driver = kernel.Driver(cfg, 100, 5)
    nxt = solver.sweep(state, driver.first(solver.add_up(state, 5, cfg.r)), 5, cfg.r)
    plan = nxt._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan and "Sort" not in plan


@pytest.mark.parametrize("seed", range(3))
def test_exact_recovery_at_twice_the_threshold(data, seed):
    fit = solver.fit_local(np.stack(data.x), Config(k=10, seed=seed), data.id.to_numpy())
    assert metrics.scores_np(rounding.round_columns(fit.factor, 10), data.truth.to_numpy())["ari"] == 1.0


def test_nfk_beats_single_lloyd_runs(spark, small):
    p = solver.local_points(planted(spark, small, 1.0))
    x, t = np.stack(p.x), p.truth.to_numpy()
    ours = [metrics.scores_np(rounding.round_columns(solver.fit_local(x, Config(k=10, seed=s), p.id.to_numpy()).factor, 10), t)["ari"] for s in range(3)]
    theirs = [metrics.scores_np(lloyd.fit_local(x, 10, s).labels, t)["ari"] for s in range(10)]
    assert min(ours) > 0.98 and np.median(theirs) < np.median(ours)


def test_step_below_the_bound_descends():
    x, _ = points(60)
    z = solver.prepare(x)
    bound = theory.smoothness_bound(0, 1.0, 3)
    cfg = Config(k=3, step=0.5 / bound, ascend=False, max_iter=40, tol_conv=1e-14, tol_dual=1e-14)
    driver = kernel.Driver(cfg, 60, 5)
    raw, dual = solver.init.raw_factor(np.arange(60), cfg.r, 0), np.zeros(60)
    c = driver.first(kernel.sums_of(z, raw, raw, dual))
    values = []
    for _ in range(30):
        f = raw * c.scale
        q = f @ f.sum(0) - 1
        values.append(-((z.T @ f) ** 2).sum() + 0.5 / 60 * (q @ q))
        raw, dual, s = kernel.fused_step(z, raw, dual, c)
        c = driver.advance(s)
    assert min(checks.descent_gaps(values, [t["move"] for t in driver.trace], 0.5 / bound, 0.0, 1.0, 3)) > -1e-10
    moves = [t["move"] for t in driver.trace]
    assert moves[-1] < moves[0]


def test_movement_shortcut_errs_where_sums_do_not():
    rng = np.random.default_rng(0)
    f = rng.random((50, 4)).astype(np.float32)
    f *= np.float32(np.sqrt(3.998 / (f.astype(float) ** 2).sum()))
    nn = float((f.astype(float) ** 2).sum())
    by_sums = math.sqrt(max(nn + nn - 2 * nn, 0) / 4)
    assert by_sums == 0 and checks.movement_shortcut(1.0, nn, 4) != by_sums


def test_centring_and_scaling_keep_the_result():
    x, _ = points()
    a = solver.fit_local(x, Config(k=3, max_iter=100)).factor
    b = solver.fit_local(7.5 * x + 100, Config(k=3, max_iter=100)).factor
    assert np.abs(a - b).max() < 1e-6


def test_breakdown_keeps_the_last_factor():
    x = np.array([[0.0, 1.0], [1.0, 0.0], [0.5, 0.5], [0.2, 0.1]])
    fit = solver.fit_local(x, Config(k=2, rank=2, step=1e9, ascend=False, max_iter=5), start=np.full((4, 2), 10.0))
    assert fit.status == "breakdown" and abs((fit.factor**2).sum() - 2) < 1e-12


@pytest.mark.parametrize("bad", [dict(k=5, rank=3), dict(k=9)])
def test_impossible_settings_are_refused(bad):
    with pytest.raises(ValueError):
        solver.fit_local(np.random.default_rng(0).random((6, 2)), Config(**bad))


def test_equal_points_are_refused():
    with pytest.raises(ValueError, match="equal"):
        solver.fit_local(np.ones((5, 2)), Config(k=2))


def test_one_cluster_and_one_point_each():
    x, _ = points(12)
    assert set(rounding.round_columns(solver.fit_local(x, Config(k=1, max_iter=50)).factor, 1)) == {0}


def test_relaxations_are_ordered(spark):
    x, _ = points(10, 2, 3)
    z = x - x.mean(0)
    g = z @ z.T
    best = brute_force_partition(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(z)], "id long, x array<double>"), 2).orderBy("id").toPandas().cluster.to_numpy()
    h = np.zeros((10, 2))
    h[np.arange(10), best] = 1 / np.sqrt(np.bincount(best, minlength=2)[best])
    part = sdp_objective(g, h @ h.T)
    assert max(sdp_feasibility(h @ h.T, 2).values()) < 1e-9
    sdp, feas = solve_sdp_small(g, 2, 800)
    assert sdp_objective(g, sdp) <= part + 0.05 * abs(part) and max(feas.values()) < 0.1
    fit = solver.fit_local(x, Config(k=2, max_iter=3000))
    assert metrics.scores_np(rounding.round_columns(fit.factor, 2), best)["ari"] == 1.0


def test_matching_against_all_permutations():
    import itertools

    rng = np.random.default_rng(3)
    for n in (1, 2, 4, 5):
        c = rng.random((n, n))
        m = metrics.matching(c)
        assert sorted(m) == list(range(n))
        assert abs(sum(c[i, j] for i, j in enumerate(m)) - min(sum(c[i, p[i]] for i in range(n)) for p in itertools.permutations(range(n)))) < 1e-12


def test_scores_of_known_cases():
    t = np.array([0, 0, 1, 1, 2, 2])
    assert metrics.scores_np(np.array([2, 2, 0, 0, 1, 1]), t) == {"ari": 1.0, "nmi": pytest.approx(1.0), "error": 0.0, "purity": 1.0}
    one = metrics.scores_np(np.zeros(6, int), t)
    assert one["ari"] == 0.0 and one["nmi"] == pytest.approx(0.0) and one["error"] == pytest.approx(2 / 3)


def test_stop_rules_are_ordered():
    x, _ = points(200, 3, 5, 2.0)
    a, b = lloyd.fit_local(x, 3, 1), lloyd.fit_local(x, 3, 1, stop="squared")
    assert b.iters <= a.iters


def test_grouped_runs_name_status_and_labels(spark):
    x, truth = points(60)
    df = spark.createDataFrame(pd.DataFrame({"id": range(60), "x": x.tolist(), "truth": truth}))
    runs = solver.fit_grouped(df, [{"method": m, "k": 3, "seed": 1} for m in ("nfk", "plain_nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped", "lloyd_restarts", "lloyd_careful", "sampled_lloyd", "spectral", "nmf", "sdp_small", "floor")])
    got = metrics.score_runs(runs, truth).toPandas()
    assert len(got) == 12 and (got[got.method.isin(["nfk", "plain_nfk", "lloyd_restarts", "floor"])].ari > 0.95).all()


def test_cost_model_of_the_largest_setting():
    n, d, _, r, _ = theory.SETTINGS[-1]
    t = theory.tiles(n, r, 128, 64)
    assert theory.buffer_bytes(n, d, r, t) == 4 * (n * d + n * r + d * r + 4 * n + 2 * r) + 24 * (t + 1)
    assert theory.fits(n, d, r, t, 141 * 10**9) and not theory.fits(n, d, r, t, 141 * 10**9, 3)


def test_products_agree_on_more_points_than_one_worker_takes(spark, monkeypatch):
    monkeypatch.setattr(solver, "local_points", lambda *a, **k: pytest.fail("points were gathered"))
    points = mixture(spark, 3_000, 16, 4, 1.0, 0, 3).select("id", "x")
    assert 0 < checks.association_gap(points, 8, tile_rows=256).first().gap < 1e-9
    x = np.array([r.x for r in points.orderBy("id").collect()])
    z, f = solver.prepare(x), init.raw_factor(np.arange(3_000), 8, 0)
    whole = solver.add_up
    monkeypatch.setattr(solver, "add_up", lambda *a: (lambda s: (s.pull.__imul__(0), s)[1])(whole(*a)))
    assert checks.association_gap(points, 8, tile_rows=256).first().gap == pytest.approx(np.abs((z @ z.T) @ f).max())


def test_points_too_many_for_one_worker_are_fitted_where_they_lie(spark, small, monkeypatch):
    from factorclust.plans import workloads

    grid = [{"method": m, "k": 10, "seed": 0, **({"max_iter": 1500} if m == "nfk" else {})} for m in ("nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped")]
    points = planted(spark, small, 2.0)
    near = {r.method: r for r in workloads.run_grid(points, "w", grid).collect()}
    monkeypatch.setattr(solver, "LOCAL_LIMIT", 1_000)
    monkeypatch.setattr(solver, "local_points", lambda *a, **k: pytest.fail("points were gathered"))
    got = workloads.run_grid(points, "w", grid)
    far = {r.method: r for r in got.collect()}
    assert got.columns == [c.split()[0] for c in metrics.SCORED.split(", ")] + ["workload"] and far.keys() == near.keys()
    a, b = near["nfk"], far["nfk"]
    assert (a.iters, a.status, a.rank, a.ari, a.error) == (b.iters, b.status, b.rank, b.ari, b.error)
    assert b.wcss == pytest.approx(a.wcss) and b.objective == pytest.approx(a.objective) and b.nmi == pytest.approx(a.nmi)
    assert all(far[m].status == "converged" and far[m].wcss >= b.wcss * 0.999 for m in far if m != "nfk")
    with pytest.raises(ValueError, match="no distributed form"):
        workloads.run_grid(points, "w", [{"method": "spectral", "k": 10}])


def test_memory_is_measured_without_moving_or_writing_points(spark, monkeypatch):
    p = mixture(spark, 6_000, 10, 4, 1.0, 0, 3)
    cfg = Config(k=4, rank=8, max_iter=3)
    want = {b: resident.fit(p, cfg, tasks=3, tile_rows=256, buffers=b, trace_memory=True) for b in (1, 3)}
    monkeypatch.setattr(resident, "_cut", lambda *a: pytest.fail("a state was written"))
    got = resident.replay(p, cfg, tile_rows=256)
    for b, m in want.items():
        peak, trace = got[b]
        assert [x["iter"] for x in trace] == [1, 2, 3] and all(x[c] == pytest.approx(y[c], rel=1e-6) for x, y in zip(trace, m.trace, strict=True) for c in ("feas", "move"))
        assert peak == pytest.approx(sum(m.peaks), rel=0.2)
    assert got[3][0] - got[1][0] > 1.5 * 8 * 6_000 * 8


def test_runs_have_tasks_of_their_own_and_step_on_threads(spark, data):
    grid = [{"method": m, "n": n, "k": 3} for m in ("lloyd_stream", "nfk") for n in (10, 40)] * 3
    parts = solver.a_run_a_task(spark, grid).rdd.glom().collect()
    assert [len(p) for p in parts] == [1] * 12 and [grid[p[0].run_id]["method"] for p in parts] == ["nfk"] * 6 + ["lloyd_stream"] * 6
    assert [grid[p[0].run_id]["n"] for p in parts[:6]] == [40] * 3 + [10] * 3
    x = np.tile(np.stack(data.x.to_numpy()), (5, 1)) + np.random.default_rng(0).normal(size=(2_500, 64)) * 0.1
    a, b = (solver.fit_local(x, Config(k=10, max_iter=50), threads=t) for t in (1, 3))
    assert np.abs(a.factor - b.factor).max() < 1e-9 and [s["dual_updates"] for s in a.trace] == [s["dual_updates"] for s in b.trace]
    labels = np.random.default_rng(1).integers(0, 7, len(x))
    sums = np.zeros((8, 64))
    np.add.at(sums, labels, x)
    assert (lloyd.sums_by(labels, x, 8) == sums).all()


def test_the_capped_baseline_is_run_however_many_points_there_are(spark, tiny, monkeypatch):
    from factorclust.plans import workloads

    monkeypatch.setattr(workloads, "CAPPED_LIMIT", 0, raising=False)
    got = {r.method: r for r in workloads.distributed_run(spark, tiny, (("part", (4, 8, 8)),), gamma=2.0).collect()}
    assert set(got) == {"nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped"}
    assert all(r.status in ("converged", "capped") and r.iters > 0 and r.ari is not None and r.total_seconds > 0 for r in got.values())
    assert got["lloyd_capped"].ari == got["lloyd_stream"].ari


@pytest.mark.parametrize("storage", ["double", "single"])
def test_a_step_in_place_is_the_fused_step(storage):
    n, d, r = 2 * kernel.STEP_ROWS + 37, 6, 8
    draw = np.random.default_rng(0)
    cfg = Config(k=4, rank=r, storage=storage)
    z, raw, dual = solver.prepare(draw.normal(size=(n, d))).astype(cfg.dtype), draw.random((n, r)).astype(cfg.dtype), draw.normal(size=n) / n
    for fire in (False, True):
        c = kernel.Control(0.3, draw.normal(size=(d, r)), draw.random(r) * 9, draw.normal(size=r), 1 / n, 0.2, fire)
        want, y, sums = kernel.fused_step(z, raw, dual, c)
        into, over, y2, y3 = np.empty_like(raw), raw.copy(), dual.copy(), dual.copy()
        got = kernel.step_rows(z, raw, y2, c, into), kernel.step_rows(z, over, y3, c)
        for f, dual2, s in ((into, y2, got[0]), (over, y3, got[1])):
            assert np.abs(f - want).max() < 1e-12 and np.abs(dual2 - y).max() < 1e-14
            assert np.allclose(s.pack(), sums.pack(), rtol=1e-10, atol=1e-10)
    control = kernel.Control(1.0, np.zeros((d, r)), np.ones(r), np.ones(r) * 99, 1.0, 9.0, False)
    assert kernel.step_rows(z, over, y3, control).nn == 0 and (over == 0).all()


def test_lloyd_in_a_stage_is_lloyd_by_jobs(spark, monkeypatch):
    points = mixture(spark, 5_000, 12, 6, 1.0, 3, 5)
    jobs = [run_costs.measure(spark, lambda: resident.lloyd_fit(points, 6, 1, max_iter=m, tasks=3))[1]["jobs"] for m in (1, 2_000)]  # noqa: B023
    assert jobs[0] == jobs[1]
    for stop in ("norm", "squared"):
        want, c, trace = lloyd.fit(points, 6, 1, stop=stop)
        for keep, kept in ((True, 1 << 20), (True, 70_000), (False, 1 << 20)):  # in memory, in part in a file, in a file
            monkeypatch.setattr(resident, "KEPT", kept)
            got, c2, trace2 = resident.lloyd_fit(points, 6, 1, stop=stop, keep=keep, tasks=3)
            assert len(trace2) == len(trace) > 3 and np.abs(c - c2).max() < 1e-9
            assert all(a["moved"] == pytest.approx(b["moved"], abs=1e-9) and a["wcss"] == pytest.approx(b["wcss"]) and a["empty"] == b["empty"] for a, b in zip(trace, trace2, strict=True))
            both = want.alias("a").join(got.alias("b"), "id").where("a.cluster = b.cluster and abs(a.distance2 - b.distance2) < 1e-6")
            assert both.count() == got.count() == 5_000


def test_a_stage_of_lloyd_keeps_an_empty_cluster(spark):
    x = np.concatenate([np.zeros((40, 2)), np.ones((40, 2)) * 9])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    got, c, trace = resident.lloyd_fit(df, 3, 0, start=np.array([[0.0, 0.1], [8.0, 8.0], [-50.0, 0.0]]), tasks=2)
    assert c.tolist() == [[0.0, 0.0], [9.0, 9.0], [-50.0, 0.0]] and trace[-1]["empty"] == 1
    assert {(r.cluster, r["count"]) for r in got.groupBy("cluster").count().collect()} == {(0, 40), (1, 40)}


def test_mixtures_too_large_for_a_task_are_fitted_where_they_lie(spark, tiny, monkeypatch):
    from factorclust.plans import workloads

    of = {"d": 16, "k": 4, "gamma": 1.5}
    grid = [{"method": m, "n": n, **of, "seed": s} for s in (0, 1) for n in (300, 5_000) for m in ("floor", "lloyd_stream", "lloyd_squared", "lloyd_capped")]
    grid += [{"method": "nfk", "n": 5_000, **of, "seed": 0, "rank": 8, "caps": [20, 60, 5_000], "max_iter": 5_000}, {"method": "nfk", "n": 5_000, **of, "seed": 1, "rank": 8, "max_iter": 30}]
    near = {(r.run_id, r["cap"]): r for r in workloads.mixture_runs(spark, grid).collect()}
    monkeypatch.setattr(solver, "LOCAL_LIMIT", 8 * 16 * 300)
    got = workloads.mixture_runs(spark, grid)
    far = {(r.run_id, r["cap"]): r for r in got.collect()}
    assert got.columns == [c.split()[0] for c in solver.MIXTURE_SCHEMA.split(", ")] and far.keys() == near.keys() and len(far) == len(grid) + 2
    for at, a in near.items():
        b = far[at]
        assert [a[c] for c in ("method", "seed", "n", "d", "k", "rank", "gamma", "iters", "status")] == [b[c] for c in ("method", "seed", "n", "d", "k", "rank", "gamma", "iters", "status")]
        assert all(a[c] == pytest.approx(b[c], rel=1e-6, abs=1e-9) for c in ("wcss", "ari", "nmi", "error")) and (a.feas is None) == (b.feas is None)
        assert a.feas is None or (a.feas == pytest.approx(b.feas, rel=1e-5) and a.move == pytest.approx(b.move, rel=1e-4))
        assert 0 < b.loop_seconds < b.total_seconds
    assert near[16, 20].error > near[16, 5_000].error and near[16, 5_000].status == "converged"
    monkeypatch.setattr(solver, "LOCAL_LIMIT", 1)
    assert workloads.balanced_run(spark, tiny, (4, 8, 8), range(1), max_iter=50).count() == 4


def test_only_the_last_snapshot_is_kept(spark, monkeypatch):
    left = []
    delete = resident._delete
    monkeypatch.setattr(resident, "_delete", lambda s, path: (left.extend(sorted(os.listdir(path.removeprefix("file://")))), delete(s, path)))
    df = mixture(spark, 600, 6, 3, 1.0, 0, 2)
    fit = resident.fit(df, Config(k=3, max_iter=45), tasks=2, save_every=10)
    assert left == ["40"] and len(fit.trace) == 45


def test_more_factor_runs_than_cores_step_on_one_thread_each(spark):
    grid = [{"method": "nfk", "n": 300, "d": 8, "k": 4, "gamma": 2.0, "seed": s, "rank": 8, "max_iter": 5} for s in range(spark.sparkContext.defaultParallelism + 1)]
    assert [r.iters for r in solver.fit_mixtures(spark, grid).collect()] == [5] * len(grid)
