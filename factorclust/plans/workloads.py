"""The experiment workloads on the given tables; all give the columns of scored runs, with the workload's name."""

from __future__ import annotations

import itertools
import time
from collections.abc import Iterable, Sequence
from functools import reduce

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import theory
from factorclust.operators import lloyd, metrics, resident, solver
from factorclust.operators.kernel import Config
from factorclust.operators.partition import means
from factorclust.sources import points as P
from factorclust.sources.tables import read_table


def run_grid(points: DataFrame, workload: str, grid: Sequence[dict]) -> DataFrame:
    """Scored runs: each in a task of its own, or, on points that are too many for one worker, one after the other by distributed fits."""
    points = cut(points)  # made once, whatever it takes to make them
    if solver.too_many(points):
        return run_far(points, workload, grid)
    truth = points.orderBy("id").select("truth").toPandas().truth.to_numpy()  # as many as a grouped fit takes
    runs = solver.fit_grouped(points, grid)
    return metrics.score_runs(runs, truth).withColumn("workload", F.lit(workload))


def run_far(points: DataFrame, workload: str, grid: Sequence[dict]) -> DataFrame:
    """The same columns from fits where the points lie; the factor's iterates are those of the local loop, Lloyd starts at portable draws."""
    spark = points.sparkSession
    truth = points.select("id", F.coalesce(F.col("truth").cast("string"), F.lit("None")).alias("label"))
    energy = points.agg(F.sum(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v))).first()[0]
    out = []
    for run_id, g in enumerate(grid):
        method, k, seed = g["method"], int(g["k"]), int(g.get("seed", 0))
        more = {c: v for c, v in g.items() if c not in ("method", "k", "seed")}
        if method == "nfk":
            model = resident.fit(points, Config(k=k, seed=seed, **more))
            labels, last, status = model.labels(), model.trace[-1], model.status
            wcss, seconds = model.wcss(), sum(x["seconds"] for x in model.trace)
            row = (model.cfg.r, 0, len(model.trace), last["feas"], last["move"], last["objective"])
        elif method in LLOYD and not more:
            labels, c, trace = lloyd.fit(points, k, seed, persist=None if method == "lloyd_stream" else StorageLevel.MEMORY_AND_DISK, **LLOYD[method])
            means, sizes, _ = lloyd.step(points, c)
            wcss, seconds = float(energy - (sizes * (means**2).sum(1)).sum()), sum(x["seconds"] for x in trace)
            status = "converged" if trace[-1]["moved"] <= lloyd.TOLERANCE else "capped"
            row = (0, 0, len(trace), None, None, None)
        else:
            raise ValueError(f"no distributed form of {g}")
        counts = metrics.contingency(labels, truth).persist()
        ari, nmi, error = metrics.ari(counts).first()[0], metrics.nmi(counts).first()[0], metrics.misclustering(counts)
        counts.unpersist()
        points.unpersist()
        out.append((run_id, method, seed, *row, wcss, seconds, status, float(ari), float(nmi), float(error)))
    return spark.createDataFrame(out, metrics.SCORED).withColumn("workload", F.lit(workload))


def mixture_runs(spark: SparkSession, grid: Sequence[dict]) -> DataFrame:
    """Scored runs on planted mixtures: each in a task of its own, or, on mixtures that are too many for one task, where the points lie, with the same starts."""
    near, far = [], {}
    for run_id, g in enumerate(grid):
        if g["n"] * g["d"] * 8 <= solver.LOCAL_LIMIT:
            near.append((run_id, g))
        else:
            far.setdefault(tuple(g[c] for c in ("n", "d", "k", "gamma", "seed")), []).append((run_id, g))
    rows = [row for data, runs in far.items() for row in far_mixture(spark, data, runs)]
    out = [spark.createDataFrame(rows, solver.MIXTURE_SCHEMA)] if rows else []
    if not far:
        return solver.fit_mixtures(spark, grid)
    if near:
        ids = F.element_at(F.array(*[F.lit(run_id).cast("long") for run_id, _ in near]), (F.col("run_id") + 1).cast("int"))
        out.append(solver.fit_mixtures(spark, [g for _, g in near]).withColumn("run_id", ids))
    return reduce(DataFrame.unionByName, out)


def far_mixture(spark: SparkSession, data: tuple, runs: Sequence[tuple[int, dict]]) -> list[tuple]:
    """Rows of solver.MIXTURE_SCHEMA of some runs on one mixture, which is written once and deleted after them."""
    n, d, k, gamma, seed = data
    points, path = solver._cut(P.mixture(spark, n, d, k, gamma, seed), solver.state_folder(spark))
    truth = points.select("id", F.col("truth").alias("label"))
    energy = points.agg(F.sum(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v))).first()[0]
    out = []
    for run_id, g in runs:
        method, began = g["method"], time.perf_counter()
        if method == "nfk":
            caps = sorted(set(g.get("caps", ())) or {0})
            model = resident.fit(points, Config(k=k, seed=seed, **{c: v for c, v in g.items() if c not in ("method", "n", "d", "k", "gamma", "seed", "caps")}), caps=caps)
            took, last = np.cumsum([x["seconds"] for x in model.trace]), len(model.trace)
            done = []
            for cap in caps:
                at = model.trace[min(cap or last, last) - 1]
                labels, wcss = (model.labels(), model.wcss()) if at["iter"] == last else (resident.labels_at(model, cap), model.wcss(cap))
                done.append((model.cfg.r, cap, at["iter"], at["feas"], at["move"], wcss, float(took[at["iter"] - 1]), model.status, labels))
        elif method == "floor" or method in LLOYD:
            if method == "floor":
                c, iters, status = np.array([r["mean"] for r in means(points, "truth").orderBy("truth").collect()]), 0, "done"  # K rows
                labels = lloyd.assign(points, c)
            else:
                start, _ = P.mixture_rows(np.random.default_rng(seed).choice(n, k, replace=False), n, d, k, gamma, seed)  # the rows that the local form draws
                labels, c, trace = resident.lloyd_fit(points, k, seed, keep=method != "lloyd_stream", start=start, **LLOYD[method])
                iters, status = len(trace), "converged" if trace[-1]["moved"] <= lloyd.TOLERANCE else "capped"
            loop = time.perf_counter() - began
            centres, sizes, _ = lloyd.step(points, c)
            done = [(0, 0, iters, None, None, float(energy - (sizes * (centres**2).sum(1)).sum()), loop, status, labels)]
        else:
            raise ValueError(f"no distributed form of {g}")
        scored = []
        for *_, labels in done:
            counts = metrics.contingency(labels, truth).persist()
            scored.append(metrics.scores_of(metrics.collected(counts)))
            counts.unpersist()
        total = time.perf_counter() - began
        for (rank, cap, iters, feas, move, wcss, loop, status, _), score in zip(done, scored, strict=True):
            out.append((run_id, method, seed, n, d, k, rank, float(gamma), cap, iters, feas, move, wcss, loop, total, status, float(score["ari"]), float(score["nmi"]), float(score["error"])))
    solver._delete(spark, path)
    return out


#: Lloyd baselines that have a distributed form, with what it takes.
LLOYD = {"lloyd_stream": {"stop": "norm", "max_iter": 10_000}, "lloyd_squared": {"stop": "squared", "max_iter": 10_000}, "lloyd_capped": {"stop": "norm", "max_iter": lloyd.CAP}}


def grid_of(methods: Iterable[str], k: int, seeds: Iterable[int], **more) -> list[dict]:
    return [{"method": m, "k": k, "seed": int(s), **(more if m in ("nfk", "plain_nfk") else {})} for m in methods for s in seeds]


def planted_run(spark: SparkSession, sf_dir: str, gamma: float, methods: Iterable[str], seeds: Iterable[int], **more) -> DataFrame:
    """Balanced classes at gamma times the threshold; one data set for all methods."""
    return run_grid(P.planted(spark, sf_dir, gamma), f"planted gamma={gamma:g}", grid_of(methods, P.CLASSES, seeds, **more))


def rank_run(spark: SparkSession, sf_dir: str, gamma: float, ranks: Iterable[int], seeds: Iterable[int], **more) -> DataFrame:
    grid = [g for r in ranks for g in grid_of(["nfk"], P.CLASSES, seeds, rank=int(r), **more)]
    return run_grid(P.planted(spark, sf_dir, gamma), f"ranks gamma={gamma:g}", grid)


def balanced_run(spark: SparkSession, sf_dir: str, setting: tuple[int, int, int], seeds: Iterable[int], methods: Iterable[str] = ("nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped"), gamma: float = 1.0, max_iter: int = 6000) -> DataFrame:
    """Balanced mixtures of a (K, d, r), as many points as there are parts, with a new data set for each seed."""
    k, d, r = setting
    n = read_table(spark, sf_dir, "part", ["p_partkey"]).count()
    grid = [{"method": m, "n": n, "d": d, "k": k, "gamma": gamma, "seed": int(s), **({"rank": r, "max_iter": max_iter} if m == "nfk" else {})} for s in seeds for m in methods]
    return mixture_runs(spark, grid)


def frontier_run(spark: SparkSession, sf_dir: str, sizes: Sequence[tuple[int, float]] = ((1, 1.0), (1, 2.0), (4, 1.0)), caps: Sequence[int] = (100, 300, 1000, 3000, 10_000, 30_000), nfk_seeds: int = 10, lloyd_seeds: int = 50) -> DataFrame:
    """Error against time for mixtures of K = 20, d = 50, r = 30 at several (times the number of customers, gamma).

    The factor runs on the first data sets, with labels at each cap; Lloyd once on each; at_floor says whose error is
    that of the nearest true mean, found on the same data. Seconds are loop seconds of the factor, all of a Lloyd run's.
    """
    base = read_table(spark, sf_dir, "customer", ["c_custkey"]).count()
    grid = []
    for times, gamma in sizes:
        of = {"n": times * base, "d": 50, "k": 20, "gamma": gamma}
        grid += [{"method": "nfk", **of, "seed": s, "rank": 30, "caps": list(caps), "max_iter": max(caps)} for s in range(nfk_seeds)]
        grid += [{"method": m, **of, "seed": s} for m in ("lloyd_stream", "floor") for s in range(lloyd_seeds)]
    got = cut(mixture_runs(spark, grid))
    floor = got.where("method = 'floor'").select("n", "gamma", "seed", F.col("error").alias("floor"))
    return got.where("method <> 'floor'").join(F.broadcast(floor), ["n", "gamma", "seed"]).withColumn("at_floor", F.col("error") <= F.col("floor") + 2e-3)


def cut(df: DataFrame) -> DataFrame:
    """Results of runs, written once so that no run is repeated."""
    return solver._cut(df, solver.state_folder(df.sparkSession))[0]


def unequal_run(spark: SparkSession, sf_dir: str, source: str, methods: Iterable[str], seeds: Iterable[int], **more) -> DataFrame:
    """Classes of very different sizes: languages of documents by letters, or thinned planted points."""
    if source == "documents":
        p = P.document_bands(spark, sf_dir).select("id", "x", "truth")
        return run_grid(p, "languages", grid_of(methods, 4, seeds, **more))
    return run_grid(P.planted(spark, sf_dir, 1.0, thin=True), "thinned", grid_of(methods, P.CLASSES, seeds, **more))


def two_bands_run(spark: SparkSession, sf_dir: str, source: str, methods: Iterable[str], seeds: Iterable[int], **more) -> DataFrame:
    """Two bands of coefficients, each at unit length."""
    if source == "documents":
        return run_grid(P.document_bands(spark, sf_dir).select("id", "x", "truth"), "bands of documents", grid_of(methods, 4, seeds, **more))
    return run_grid(P.half_bands(P.planted(spark, sf_dir, 1.0)), "bands of planted halves", grid_of(methods, P.CLASSES, seeds, **more))


#: Tables whose sizes the distributed mixtures take, with (K, d, r).
MIXTURES = (("events", (20, 50, 30)), ("orders", (20, 50, 30)))
LARGEST = (("lineitem", (20, 50, 60)),)


def distributed_run(spark: SparkSession, sf_dir: str, tables: Sequence[tuple[str, tuple[int, int, int]]] = MIXTURES, gamma: float = 1.0, seed: int = 0, max_iter: int = 6000) -> DataFrame:
    """Balanced mixtures with as many points as a table has rows, made where they are used; the factor and three Lloyd baselines, all distributed.

    The streaming baseline reads its points anew for each sweep, from files of its tasks; the others keep them. Each is run to
    its end on all points, however many. Total seconds are of the whole fit with its labels, loop seconds of the iterations alone.
    """
    out = []
    for table, (k, d, r) in tables:
        n = read_table(spark, sf_dir, table).count()
        points = P.mixture(spark, n, d, k, gamma, seed)
        truth = points.select("id", F.col("truth").alias("label"))
        for method in ("nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped"):
            began = time.perf_counter()
            if method == "nfk":
                model = resident.fit(points, Config(k=k, rank=r, seed=seed, max_iter=max_iter))
                labels, trace, status, loop = model.labels(), model.trace, model.status, sum(x["seconds"] for x in model.trace)
            else:
                labels, _, trace = resident.lloyd_fit(points, k, seed, keep=method != "lloyd_stream", **LLOYD[method])
                status, loop = "converged" if trace[-1]["moved"] <= lloyd.TOLERANCE else "capped", sum(x["seconds"] for x in trace)
            counts = metrics.contingency(labels, truth).persist()
            row = metrics.ari(counts).join(metrics.nmi(counts)).first()
            error = metrics.misclustering(counts)
            counts.unpersist()
            out.append((table, method, n, d, k, r, len(trace), status, float(row.ari), float(row.nmi), float(error), float(loop), time.perf_counter() - began))
    spark.catalog.clearCache()
    return spark.createDataFrame(out, "workload string, method string, n long, d int, k int, rank int, iters int, status string, ari double, nmi double, error double, loop_seconds double, total_seconds double")


def boxes(results: DataFrame) -> DataFrame:
    """Quartiles and range of each measure over the runs of a method and workload."""
    long = results.select("workload", "method", F.explode(F.create_map(*[x for c in ("ari", "nmi", "error", "seconds", "iters") for x in (F.lit(c), F.col(c).cast("double"))])).alias("metric", "value"))
    return metrics.summarise(long, ["workload", "method", "metric"], "value")


def memory_run(spark: SparkSession, settings: Sequence[tuple[int, int, int, int, int]] = theory.SETTINGS, device_bytes: int = 141_000_000_000) -> DataFrame:
    """Bytes with one and three factor buffers, and whether a device of the given size holds them."""
    rows = []
    for n, d, k, r, _ in settings:
        one = theory.buffer_bytes(n, d, r, theory.tiles(n, r, 128, 64))
        for b in (1, 3):
            total = one + (b - 1) * 4 * n * r
            rows.append((n, d, k, r, b, total, total <= device_bytes))
    return spark.createDataFrame(rows, "n long, d long, k long, r long, buffers int, bytes long, fits boolean")


def ml_scores(spark: SparkSession, points: DataFrame, k: int, seed: int) -> DataFrame:
    from pyspark.ml.clustering import BisectingKMeans, GaussianMixture, KMeans
    from pyspark.ml.functions import array_to_vector

    data = points.select("id", "truth", array_to_vector("x").alias("features")).persist()
    out = []
    for name, model in (("ml_parallel", KMeans(k=k, seed=seed, maxIter=50)), ("ml_random", KMeans(k=k, seed=seed, initMode="random", maxIter=50)), ("ml_bisecting", BisectingKMeans(k=k, seed=seed)), ("ml_mixture", GaussianMixture(k=k, seed=seed, maxIter=10))):
        got = model.fit(data).transform(data).groupBy(F.col("prediction").alias("cluster"), F.col("truth").alias("label")).agg(F.count(F.lit(1)).alias("n"))
        row = metrics.ari(got).join(metrics.nmi(got)).first()
        out.append((name, float(row.ari), float(row.nmi), metrics.misclustering(got)))
    data.unpersist()
    return spark.createDataFrame(out, "method string, ari double, nmi double, error double")


def best_of(results: DataFrame, tol: float = 1e-3) -> DataFrame:
    """The run to keep, without labels: feasible with the least objective, else the least sum of squares."""
    order = F.struct((F.coalesce(F.col("feas") < tol, F.lit(False)) == F.lit(False)).alias("infeasible"), F.when(F.col("feas") < tol, F.col("objective")).otherwise(F.col("wcss")).alias("value"))
    return results.groupBy("workload", "method").agg(F.min_by("run_id", order).alias("run_id"), F.min_by("seed", order).alias("seed"), F.min_by("error", order).alias("error"))


# --- uses -------------------------------------------------------------------------------------------------------


def fit_labels(points: DataFrame, k: int, seed: int = 0, **more) -> DataFrame:
    """(id, cluster) of one grouped fit."""
    runs = solver.fit_grouped(points, [{"method": "nfk", "k": k, "seed": seed, **more}])
    return solver.labels_of_runs(points, runs).select("id", "cluster")


def dedup_groups(points: DataFrame, labels: DataFrame, cosine: float = 0.99) -> DataFrame:
    """(a, b, cosine) of pairs within a cluster above a cosine.

    Unit vectors with a cosine of c lie at most sqrt(2 - 2 c) apart, in each component too; so rows are dealt into
    cells of that width by the two components that vary most, and only rows of neighbouring cells meet.
    """
    from factorclust.functions import vectors

    far = max(1e-9, float(np.sqrt(max(0.0, 2 - 2 * cosine))))
    unit = points.join(labels, "id").select("id", "cluster", vectors.unit(F.col("x")).alias("u"))
    d = unit.select(F.max(F.size("u"))).first()[0] or 1
    spread = unit.select(*[F.var_pop(F.get("u", j)).alias(str(j)) for j in range(d)]).first()
    axes = sorted(range(d), key=lambda j: -(spread[j] or 0))[:2]
    cell = lambda j: F.floor(F.get("u", j) / far).cast("long")
    celled = unit.withColumn("cell", F.array(*[cell(j) for j in axes]))
    near = F.array(*[F.array(*[F.get("cell", i) + s for i, s in enumerate(shift)]) for shift in itertools.product((-1, 0, 1), repeat=len(axes))])
    a = celled.select(F.col("id").alias("a"), "cluster", F.col("u").alias("ua"), "cell")
    b = celled.select(F.col("id").alias("b"), "cluster", F.col("u").alias("ub"), F.explode(near).alias("cell"))
    return a.join(b, ["cluster", "cell"]).where("a < b").select("a", "b", vectors.dot(F.col("ua"), F.col("ub")).alias("cosine")).where(F.col("cosine") >= cosine)


def retrieve(points: DataFrame, centroids: np.ndarray, queries: DataFrame, probe: int = 2, k: int = 5) -> DataFrame:
    """(query, id, distance2, rank): the k nearest rows in the clusters of the ``probe`` nearest centroids."""
    from factorclust.functions import vectors
    from factorclust.operators import lloyd
    from pyspark.sql import Window

    assigned = lloyd.assign(points, centroids).select("id", "cluster").join(points.select("id", "x"), "id")
    c = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in centroids])
    dist = F.transform(c, lambda m, i: F.struct(vectors.sqdist(F.col("x"), m).alias("d"), i.alias("cluster")))
    probes = queries.select(F.col("id").alias("query"), F.col("x").alias("q"), F.explode(F.slice(F.array_sort(dist), 1, probe)).alias("p")).select("query", "q", F.col("p.cluster").alias("cluster"))
    near = assigned.join(probes, "cluster").select("query", "id", vectors.sqdist(F.col("x"), F.col("q")).alias("distance2"))
    rank = F.row_number().over(Window.partitionBy("query").orderBy("distance2", "id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k)


def profile_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, x: balance, orders, spend, items, mean discount of each customer with orders, standardised."""
    c = read_table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"])
    o = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice"])
    li = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity", "l_discount"])
    per_order = li.groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"), F.sum("l_discount").alias("disc"), F.count(F.lit(1)).alias("lines"))
    per = o.join(per_order, o.o_orderkey == per_order.l_orderkey, "left").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("orders"), F.sum("o_totalprice").alias("spend"), F.coalesce(F.sum("q"), F.lit(0.0)).alias("items"), F.coalesce(F.sum("disc") / F.sum("lines"), F.lit(0.0)).alias("disc"))
    return c.join(per, c.c_custkey == per.o_custkey).select(F.col("c_custkey").alias("id"), "c_acctbal", "orders", "spend", "items", "disc")


def standardised(df: DataFrame, key: str, columns: Sequence[str]) -> DataFrame:
    s = df.agg(*[f(c).alias(f"{n}_{c}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    return df.select(F.col(key).cast("long").alias("id"), F.array(*[((F.col(c) - float(s[f"m_{c}"])) / float(s[f"s_{c}"] or 1)).cast("double") for c in columns]).alias("x"))


def group_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, x: counts of some tags and the length of each page."""
    p = read_table(spark, sf_dir, "pages", ["page_id", "html"])
    tags = ("<p>", "<a ", "<li>", "<div", "<script", "<h1>")
    return standardised(p.select("page_id", *[F.regexp_count("html", F.lit(t)).cast("double").alias(f"t{i}") for i, t in enumerate(tags)], F.length("html").cast("double").alias("len")), "page_id", [f"t{i}" for i in range(len(tags))] + ["len"])


def group_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, x: length, words and place of each turn of a conversation."""
    t = read_table(spark, sf_dir, "conversations", ["conv_id", "turn", "text"])
    return standardised(t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("k"), F.length("text").cast("double").alias("len"), F.size(F.split("text", " ")).cast("double").alias("words"), F.col("turn").cast("double").alias("place")), "k", ["len", "words", "place"])
