"""End-to-end fits, baselines and workloads as queries."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import portable, theory, vectors
from factorclust.operators import checks, lloyd, metrics, paired, resident, solver
from factorclust.operators.kernel import Config
from factorclust.plans import workloads
from factorclust.plans.pieces import CFG, r6, run_steps
from factorclust.registry import register
from factorclust.sources.points import from_embeddings, planted
from factorclust.sources.tables import read_table


@register("select vec_id as id, label as cluster from embeddings")
def nfk_planted_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At twice the threshold the labels are recovered exactly; clusters are named by their majority label."""
    p = planted(spark, sf_dir, 2.0)
    runs = solver.fit_grouped(p, [{"method": "nfk", "k": 10, "seed": 0}])
    got = solver.labels_of_runs(p, runs).select("id", "cluster")
    named = got.join(p.select("id", "truth"), "id").groupBy("cluster", "truth").count()
    name = named.groupBy("cluster").agg(F.max_by("truth", F.struct("count", -F.col("truth"))).alias("name"))
    return got.join(F.broadcast(name), "cluster").select("id", F.col("name").alias("cluster"))


@register("select s::INTEGER as seed, 1.0::DOUBLE as ari, 1.0::DOUBLE as nmi, 0.0::DOUBLE as error from (select unnest(range(3)) as s)")
def nfk_planted_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = workloads.planted_run(spark, sf_dir, 2.0, ["nfk"], range(3))
    return got.select("seed", *[r6(F.col(c)).alias(c) for c in ("ari", "nmi", "error")])


@register("select 'converged' as status, 1.0::DOUBLE as ari, count(*)::BIGINT as points, true as several_tasks from embeddings")
def nfk_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distributed solver to its own stop rule, on points and factor that stay in the tasks; its own status and the score of its own labels."""
    p = planted(spark, sf_dir, 2.0)
    far = resident.fit(p.select("id", "x"), Config(k=10, seed=1), tasks=min(4, spark.sparkContext.defaultParallelism))
    table = metrics.contingency(far.labels(), p.select("id", F.col("truth").alias("label")))
    return metrics.ari(table).select(F.lit(far.status).alias("status"), F.round("ari", 6).alias("ari"), F.lit(far.state.agg(F.sum("rows")).first()[0]).alias("points"), F.lit(far.tasks > 1).alias("several_tasks"))


@register("select * from (values ('a job an iteration', true), ('in tables', true), ('single precision', true), ('stays in tasks', true)) t(form, same)")
def nfk_distributed_same_iterates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distributed forms step as the local solver does: five iterations, or 200 where points stay in tasks."""
    p = planted(spark, sf_dir, 2.0)
    x = p.select("id", "x")
    pdf = solver.local_points(p)
    rows = []
    for form, fit, iters, tol, storage in (
        ("a job an iteration", lambda c: solver.fit_distributed(x, c, tile_rows=128), 5, 1e-8, "double"), ("in tables", lambda c: paired.fit(x, c, buckets=2, tile_rows=128), 5, 1e-8, "double"),
        ("single precision", lambda c: solver.fit_distributed(x, c, tile_rows=128), 5, 1e-5, "single"), ("stays in tasks", lambda c: resident.fit(x, c, tasks=2), 200, 1e-6, "double"),
    ):
        near = solver.fit_local(np.stack(pdf.x.to_numpy()), Config(k=10, max_iter=iters, seed=1), pdf.id.to_numpy())
        far = fit(Config(k=10, max_iter=iters, seed=1, storage=storage))
        rows.append((form, len(far.trace) == len(near.trace) and max(abs(a[c] - b[c]) for a, b in zip(far.trace, near.trace, strict=True) for c in ("feas", "move")) < tol))
    paired.drop_tables(spark)
    return spark.createDataFrame([(f, bool(b)) for f, b in rows], "form string, same boolean")


@register("select true as same_factor, true as same_trace")
def nfk_vs_plain_same_iterates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fused pass and the three-buffer form step alike."""
    pdf = solver.local_points(planted(spark, sf_dir, 1.0))
    x, ids = np.stack(pdf.x.to_numpy()), pdf.id.to_numpy()
    cfg = Config(k=10, max_iter=60, seed=2)
    a, b = solver.fit_local(x, cfg, ids), solver.fit_threebuffer(x, cfg, ids)
    trace = all(abs(s[c] - t[c]) < 1e-9 for s, t in zip(a.trace, b.trace, strict=True) for c in ("move", "feas"))
    return spark.createDataFrame([(bool(np.abs(a.factor - b.factor).max() < 1e-9), trace)], "same_factor boolean, same_trace boolean")


@register()
def nfk_seed_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.planted_run(spark, sf_dir, 1.0, ["nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped", "lloyd_restarts", "lloyd_careful", "floor"], range(4))


@register()
def nfk_rank_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.rank_run(spark, sf_dir, 1.0, ranks=(10, 15, 20, 30), seeds=range(2), max_iter=2000)


@register()
def nfk_cap_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error against time on mixtures with K = 20, d = 50 at three (n, gamma): 50 data sets for Lloyd, ten of them for the factor at six caps."""
    return workloads.frontier_run(spark, sf_dir)


@register("select * from (values (1.0::DOUBLE, true, true), (2.0::DOUBLE, true, true)) t(gamma, factor_at_floor, lloyd_seldom)")
def nfk_frontier_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where the factor's runs end at the floor on all matched data sets, and single Lloyd runs on less than half of theirs."""
    got = workloads.frontier_run(spark, sf_dir, sizes=((1, 1.0), (1, 2.0)), caps=(300, 6000), nfk_seeds=10, lloyd_seeds=50)
    last = got.where("method <> 'nfk' or cap = 6000").groupBy("gamma").agg(F.avg(F.when(F.col("method") == "nfk", F.col("at_floor").cast("int"))).alias("ours"), F.avg(F.when(F.col("method") == "lloyd_stream", F.col("at_floor").cast("int"))).alias("theirs"))
    return last.select("gamma", (F.col("ours") == 1).alias("factor_at_floor"), (F.col("theirs") < 0.5).alias("lloyd_seldom"))


@register()
def nfk_new_data_a_seed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The balanced benchmark at gamma 1: 20 seeds, each with a data set of its own for all methods."""
    return workloads.balanced_run(spark, sf_dir, (20, 50, 30), range(20))


@register()
def nfk_large_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The setting with K = 100, d = 200, r = 300, at gamma 2 and 1,000 iterations at most; one seed (the local loop takes minutes a run)."""
    return workloads.balanced_run(spark, sf_dir, (100, 200, 300), range(1), methods=("nfk", "lloyd_stream", "lloyd_squared"), gamma=2.0, max_iter=1000)


@register()
def nfk_mixture_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mixtures as large as events and orders, fitted where the points lie, beside distributed Lloyd runs."""
    return workloads.distributed_run(spark, sf_dir)


@register()
def nfk_mixture_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same as large as lineitem, with r = 60 as in the largest published setting."""
    return workloads.distributed_run(spark, sf_dir, workloads.LARGEST)


@register()
def nfk_thinned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of unequal sizes, 100 seeds."""
    return workloads.unequal_run(spark, sf_dir, "thinned", ["nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped"], range(100))


@register("select true as best_median")
def nfk_thinned_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On classes of unequal sizes the factor's median NMI is above each Lloyd baseline's."""
    got = workloads.unequal_run(spark, sf_dir, "thinned", ["nfk", "lloyd_stream", "lloyd_squared", "lloyd_capped"], range(20))
    median = got.groupBy("method").agg(F.percentile("nmi", F.lit(0.5)).alias("m"))
    return median.agg((F.max(F.when(F.col("method") == "nfk", F.col("m"))) > F.max(F.when(F.col("method") != "nfk", F.col("m")))).alias("best_median"))


@register()
def nfk_documents_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.unequal_run(spark, sf_dir, "documents", ["nfk", "lloyd_stream", "lloyd_squared"], range(3), max_iter=1500)


@register()
def nfk_two_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.two_bands_run(spark, sf_dir, "halves", ["nfk", "lloyd_stream", "lloyd_squared"], range(5))


@register()
def nfk_document_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two bands of letter counts of documents, each at unit length, five seeds: mean and median NMI."""
    got = workloads.two_bands_run(spark, sf_dir, "documents", ["nfk", "lloyd_stream", "lloyd_squared"], range(5), max_iter=1000)
    return got.groupBy("method").agg(F.avg("nmi").alias("mean_nmi"), F.percentile("nmi", F.lit(0.5)).alias("median_nmi"), F.percentile("seconds", F.lit(0.5)).alias("median_seconds"), F.count(F.lit(1)).alias("runs"))


@register()
def workload_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.boxes(workloads.planted_run(spark, sf_dir, 1.0, ["nfk", "lloyd_stream"], range(4)))


@register()
def relaxation_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The other methods on all planted points; only the convex relaxation, of n x n numbers, on a slice of them."""
    p = planted(spark, sf_dir, 2.0)
    few = p.where("id < 120 and truth < 4")
    scored = []
    for points, k, methods in ((p, 10, ("nfk", "plain_nfk", "spectral", "nmf", "sampled_lloyd", "floor")), (few, 4, ("sdp_small",))):
        runs = solver.fit_grouped(points, [{"method": m, "k": k, "seed": 0} for m in methods])
        scored.append(metrics.score_runs(runs, solver.local_points(points).truth.to_numpy()).drop("seconds").withColumn("n", F.lit(points.count())))
    return scored[0].unionByName(scored[1])


@register()
def mlkmeans_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spark's own clusterers as an outside reference."""
    return workloads.ml_scores(spark, planted(spark, sf_dir, 2.0), 10, 1)


@register("select step::BIGINT as step, true as falls from (select unnest(range(1, 6)) as step)")
def descent_gap_small_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With the dual at rest and a step below the bound, each step lowers the Lagrangian by what the bound promises."""
    from factorclust.operators.checks import descent_gaps, lagrangian

    bound = theory.smoothness_bound(0.0, CFG.penalty, CFG.k)
    step = 0.5 / bound
    cfg = Config(k=CFG.k, rank=CFG.rank, step=step, ascend=False, seed=CFG.seed, tol_conv=1e-12, tol_dual=1e-12)
    values, moves = [], []
    for t in range(6):
        rows, _, driver, (_, _, stats) = run_steps(spark, sf_dir, t, cfg)
        values.append(lagrangian(rows, stats["n"], cfg.penalty).first()[0])
    moves = [x["move"] for x in driver.trace]
    gaps = descent_gaps(values, moves, step, 0.0, cfg.penalty, cfg.k)
    return spark.createDataFrame([(i + 1, bool(g >= -1e-10)) for i, g in enumerate(gaps)], "step long, falls boolean")


@register("select true as grows_plain, true as steady_scaled, (select count(*) from embeddings)::BIGINT as few, (select count(*) from orders)::BIGINT as many")
def penalty_gradient_growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The norm of the penalty's gradient at the portable start of few and of many rows: it grows with n in the plain form, not in the scaled one."""
    norms: dict[tuple[bool, int], float] = {}
    sizes = []
    for table, key in (("embeddings", "vec_id"), ("orders", "o_orderkey")):
        ids = read_table(spark, sf_dir, table, [key]).select(F.col(key).cast("long").alias("id"))
        raw = ids.select("id", F.array(*[portable.uniform(F.col("id"), j, 1) for j in range(8)]).alias("f"))
        n, norm2 = raw.agg(F.count(F.lit(1)), F.sum(vectors.norm2(F.col("f")))).first()
        rows = raw.select("id", vectors.scale(F.lit(float(np.sqrt(4 / norm2))), F.col("f")).alias("f"))
        sizes.append(int(n))
        for scaled in (True, False):
            norms[scaled, len(sizes)] = checks.penalty_gradient_norm(rows, n, 1.0, scaled)
    grows = norms[False, 2] > 0.5 * np.sqrt(sizes[1] / sizes[0]) * norms[False, 1]
    return spark.createDataFrame([(bool(grows), bool(norms[True, 2] < 1.5 * norms[True, 1]), *sizes)], "grows_plain boolean, steady_scaled boolean, few long, many long")


# --- Lloyd ------------------------------------------------------------------------------------------------------

_START = "c0 as (select label as c, j, avg(v) as v from e where id < 100 group by label, j)"
_E = "e as materialized (select vec_id as id, label, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j))"


def _lloyd_sql(steps: int) -> str:
    out = [_E, _START]
    for t in range(steps):
        out += [
            f"d{t} as materialized (select e.id, c.c, sum((e.v - c.v) * (e.v - c.v)) as d from e join c{t} c on c.j = e.j group by e.id, c.c)",
            f"a{t} as materialized (select id, c, d from (select *, row_number() over (partition by id order by round(d, 12), c) as rn from d{t}) where rn = 1)",
            f"m{t} as materialized (select a.c, e.j, avg(e.v) as v from a{t} a join e on e.id = a.id group by a.c, e.j)",
            f"c{t + 1} as materialized (select o.c, o.j, coalesce(m.v, o.v) as v from c{t} o left join m{t} m on m.c = o.c and m.j = o.j)",
        ]
    return "with " + ", ".join(out)


def start_centroids(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, np.ndarray]:
    """Points, and the means of the first hundred rows' labels."""
    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    rows = means(p.where("id < 100"), "truth").orderBy("truth").collect()  # ten rows
    return p, np.array([r["mean"] for r in rows])


@register(_lloyd_sql(1) + " select c::INTEGER as cluster, count(*) as size, round(sum(d), 6) as wcss from a0 group by c")
def lloyd_one_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, c = start_centroids(spark, sf_dir)
    return lloyd.assign(p, c).groupBy("cluster").agg(F.count(F.lit(1)).alias("size"), F.round(F.sum("distance2"), 6).alias("wcss"))


@register(_lloyd_sql(3) + " select id, c::INTEGER as cluster from a2")
def lloyd_three_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, c = start_centroids(spark, sf_dir)
    for _ in range(2):
        c, _, _ = lloyd.step(p, c)
    return lloyd.assign(p, c).select("id", "cluster")


@register(_lloyd_sql(2) + ", s as (select c, sqrt(sum((a.v - b.v) * (a.v - b.v))) as far from c1 a join c0 b using (c, j) group by c) select round(sqrt(sum(far * far)), 6) as norm, round(sum(far * far), 6) as squared, round(max(far), 6) as largest from s")
def lloyd_stop_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The movement after one step by each rule."""
    p, c = start_centroids(spark, sf_dir)
    new, _, _ = lloyd.step(p, c)
    rows = [tuple(round(lloyd.movement(c, new, rule), 6) for rule in ("norm", "squared", "max"))]
    return spark.createDataFrame(rows, "norm double, squared double, largest double")


@register(_lloyd_sql(2) + " select round((select sum(d) from a0), 6) as first, round((select sum(d) from a1), 6) as second, round(((select sum(d) from a0) - (select sum(d) from a1)) / (select sum(d) from a0), 9) as fall")
def lloyd_objective_rule(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The within sums of two sweeps, and what the objective rule makes of them."""
    p, c = start_centroids(spark, sf_dir)
    new, _, first = lloyd.step(p, c)
    _, _, second = lloyd.step(p, new)
    return spark.createDataFrame([(round(first, 6), round(second, 6), round(lloyd.fall(first, second), 9))], "first double, second double, fall double")


@register("select 0::BIGINT as size, true as kept")
def lloyd_empty_cluster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A centroid that no point is near stays where it is."""
    p, c = start_centroids(spark, sf_dir)
    c = np.vstack([c, np.full(64, 100.0)])
    new, sizes, _ = lloyd.step(p, c)
    return spark.createDataFrame([(int(sizes[-1]), bool((new[-1] == c[-1]).all()))], "size long, kept boolean")


@register(f"with {_E}, o as (select j, v from e where id = 0) select e.id, round(sum((e.v - o.v) * (e.v - o.v)), 6) as weight from e join o using (j) group by e.id")
def dsq_seed_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights of the second draw of careful seeding, with id 0 first."""
    p = from_embeddings(spark, sf_dir)
    first = p.where("id = 0").select(F.col("x").alias("o"))
    return p.join(F.broadcast(first)).select("id", F.round(vectors.sqdist(F.col("x"), F.col("o")), 6).alias("weight"))


_FLOOR = f"with {_E}, m as (select label, j, avg(v) as v from e group by label, j), d as (select e.id, m.label as c, sum((e.v - m.v) * (e.v - m.v)) as d from e join m using (j) group by e.id, m.label)"


@register(f"{_FLOOR} select id, c as cluster from (select *, row_number() over (partition by id order by round(d, 12), c) as rn from d) where rn = 1")
def bayes_floor_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest true class mean."""
    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    m = np.array([r["mean"] for r in means(p, "truth").orderBy("truth").collect()])  # ten rows
    return lloyd.assign(p, m).select("id", "cluster")


@register(f"with {_E}, c as (select label as c, j, avg(v) as v from e where id % 5 = 0 group by label, j), d as (select e.id, c.c, sum((e.v - c.v) * (e.v - c.v)) as d from e join c using (j) group by e.id, c.c) select c as cluster, count(*) as size from (select *, row_number() over (partition by id order by round(d, 12), c) as rn from d) where rn = 1 group by c")
def sampled_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centres of a fifth of the rows, then all rows assigned."""
    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    m = np.array([r["mean"] for r in means(p.where("id % 5 = 0"), "truth").orderBy("truth").collect()])  # ten rows
    return lloyd.assign(p, m).groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
