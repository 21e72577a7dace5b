"""Each quantity of a solver step as a query, on the raw embeddings with a portable start and a fixed scale.

The Spark side runs the distributed sweep and reads its state; the SQL side redoes the steps in relational
form from the formulas, row by row and entry by entry.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import portable, vectors
from factorclust.operators import solver
from factorclust.operators.kernel import Config, Driver
from factorclust.operators.normalize import column_stats
from factorclust.registry import register
from factorclust.sources.points import from_embeddings

#: The queries' own choices: clusters, rank, step, and a scale in place of the spectral norm.
K, R, STEP, SIGMA, SEED, D = 4, 8, 0.05, 3.0, 5, 64
CFG = Config(k=K, rank=R, step=STEP, seed=SEED, tol_dual=0.05, tol_conv=1e-9, max_iter=1000)


def run_steps(spark: SparkSession, sf_dir: str, steps: int, cfg: Config = CFG) -> tuple[DataFrame, float, Driver, object]:
    """(state rows after the steps, scale, driver, the sums of the last sweep)."""
    points = from_embeddings(spark, sf_dir).select("id", "x")
    stats = column_stats(points)
    state = solver.build_tiles(points, stats["mean"], SIGMA, cfg)
    driver = Driver(cfg, stats["n"], stats["d"])
    sums = solver.add_up(state, D, R)
    control = driver.first(sums)
    for _ in range(steps):
        state = solver.sweep(state, control, D, R)
        sums = solver.add_up(state, D, R)
        control = driver.advance(sums)
    return rows_of(state, driver.scale), driver.scale, driver, (sums, control, stats)


def rows_of(state: DataFrame, scale: float) -> DataFrame:
    """(id, z, f, dual) rows of a state."""

    def run(batches):
        import pyarrow as pa

        lists = lambda m: pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1) * m.shape[1], pa.int32()), pa.array(m.ravel()))
        for b in batches:
            for ids, z, raw, dual in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                n = len(ids) // 8
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(ids, np.int64)), lists(np.frombuffer(z).reshape(n, -1)), lists(np.frombuffer(raw).reshape(n, -1) * scale), pa.array(np.frombuffer(dual))], names=["id", "z", "f", "dual"])

    return state.select("ids", "z", "raw", "dual").mapInArrow(run, "id long, z array<double>, f array<double>, dual double")


def r6(c, digits: int = 6):
    return F.round(c, digits) + F.lit(0.0)


def entries(rows: DataFrame, column: str, index: str, value: str) -> DataFrame:
    return rows.select("id", F.posexplode(column).alias(index, value))


def column_sums(rows: DataFrame) -> list[float]:
    out = [0.0] * R
    for r in entries(rows, "f", "c", "v").groupBy("c").agg(F.sum("v").alias("s")).collect():  # r rows
        out[r.c] = r.s
    return out


def literal(v) -> F.Column:
    return F.array(*[F.lit(float(x)) for x in v])


def residual(rows: DataFrame) -> DataFrame:
    return rows.withColumn("resid", vectors.dot(F.col("f"), literal(column_sums(rows))) - 1)


# --- the same in SQL --------------------------------------------------------------------------------------------


def chain(steps: int) -> str:
    """CTEs up to the factor ``f{steps}`` with everything on the way."""
    out = [
        "mean as (select j, avg(embedding[j + 1]::DOUBLE) as m from embeddings, (select unnest(range(64)) as j) group by j)",
        f"z as (select vec_id as id, e.j, (embedding[e.j + 1]::DOUBLE - m) / {SIGMA} as v from embeddings, mean e)",
        "cnt as (select count(*) as n from embeddings)",
        f"u0 as (select vec_id as id, c, {portable.uniform_sql('vec_id', 'c', SEED)} as v from embeddings, (select unnest(range({R})) as c))",
        f"f0 as (select id, c, v * sqrt({K} / (select sum(v * v) from u0)) as v from u0)",
        "dual0 as (select vec_id as id, 0.0::DOUBLE as v from embeddings)",
    ]
    for t in range(steps):
        out += [
            *_sides(t),
            f"pull{t} as (select z.j, f.c, sum(z.v * f.v) as v from z join f{t} f on f.id = z.id group by z.j, f.c)",
            f"eff{t} as (select r.id, d.v + r.v / (select n from cnt) as v from resid{t} r join dual{t} d on d.id = r.id)",
            f"shift{t} as (select f.c, sum(f.v * e.v) as v from f{t} f join eff{t} e on e.id = f.id group by f.c)",
            f"prod{t} as (select z.id, p.c, sum(z.v * p.v) as v from z join pull{t} p on p.j = z.j group by z.id, p.c)",
            f"w{t} as (select f.id, f.c, greatest(f.v + {2 * STEP} * p.v - {STEP} * e.v * s.v - {STEP} * h.v, 0.0) as v, f.v as old from f{t} f join prod{t} p on p.id = f.id and p.c = f.c join eff{t} e on e.id = f.id join colsum{t} s on s.c = f.c join shift{t} h on h.c = f.c)",
            f"st{t} as (select sum(v * v) as nn, sum(old * old) as oo, sum(v * old) as no, sqrt({K} / sum(v * v)) as scale from w{t})",
            f"mv{t} as (select sqrt(greatest(scale * scale * nn + oo - 2 * scale * no, 0) / {K}) as v from st{t})",
            f"f{t + 1} as (select id, c, v * (select scale from st{t}) as v from w{t})",
            *_sides(t + 1)[: (2 if t + 1 == steps else 0)],
        ]
        # the dual moves with the residual of the new factor
        side = [] if t + 1 == steps else _sides(t + 1)
        out += side
        out.append(f"dual{t + 1} as (select d.id, case when (select v from mv{t}) < {CFG.tol_dual} then d.v + r.v / (select n from cnt) else d.v end as v from dual{t} d join resid{t + 1} r on r.id = d.id)")
    if steps == 0:
        out += _sides(0)
    seen: set[str] = set()
    unique = [x for x in out if not (x.split(" ", 1)[0] in seen or seen.add(x.split(" ", 1)[0]))]
    # the joins of entries would otherwise be done again for each use
    return "with " + ",\n".join(x.replace(" as (", " as materialized (", 1) for x in unique)


def _sides(t: int) -> list[str]:
    return [
        f"colsum{t} as (select c, sum(v) as v from f{t} group by c)",
        f"resid{t} as (select f.id, sum(f.v * s.v) - 1 as v from f{t} f join colsum{t} s on s.c = f.c group by f.id)",
    ]


@register(f"{chain(0)} select id, c as j, round(v, 6) + 0.0 as f from f0")
def init_factor_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, *_ = run_steps(spark, sf_dir, 0)
    return entries(rows, "f", "j", "v").select("id", F.col("j").cast("long"), r6(F.col("v")).alias("f"))


@register(f"{chain(0)} select c as j, round(v, 6) + 0.0 as colsum from colsum0")
def factor_colsum(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, *_ = run_steps(spark, sf_dir, 0)
    return entries(rows, "f", "j", "v").groupBy(F.col("j").cast("long").alias("j")).agg(r6(F.sum("v")).alias("colsum"))


@register(f"{chain(0)} select id, round(v, 6) + 0.0 as resid from resid0")
def row_residual(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, *_ = run_steps(spark, sf_dir, 0)
    return residual(rows).select("id", r6(F.col("resid")).alias("resid"))


@register(f"{chain(1)} select id, round(v, 9) + 0.0 as eff from eff0")
def eff_dual(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, _, driver, _ = run_steps(spark, sf_dir, 0)
    return residual(rows).select("id", r6(F.col("dual") + driver.weight * F.col("resid"), 9).alias("eff"))


@register(f"{chain(1)} select j as i, c as j, round(v, 6) + 0.0 as pull from pull0")
def pull_moment(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, scale, _, (sums, _, _) = run_steps(spark, sf_dir, 0)
    rows = [(i, j, float(sums.pull[i, j] * scale)) for i in range(D) for j in range(R)]
    return spark.createDataFrame(rows, "i long, j long, v double").select("i", "j", r6(F.col("v")).alias("pull"))


@register(f"{chain(1)} select c as j, round(v, 6) + 0.0 as shift from shift0")
def shift_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factorclust.operators.kernel import Driver as Fresh

    _, _, driver, (sums, _, stats) = run_steps(spark, sf_dir, 0)
    control = Fresh(CFG, stats["n"], stats["d"]).first(sums)
    return spark.createDataFrame([(j, float(v)) for j, v in enumerate(control.shift)], "j long, v double").select("j", r6(F.col("v")).alias("shift"))


@register(f"{chain(1)} select id, c as j, round(v, 6) + 0.0 as raw from w0")
def raw_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, scale, *_ = run_steps(spark, sf_dir, 1)
    return entries(rows, "f", "j", "v").select("id", F.col("j").cast("long"), r6(F.col("v") / scale).alias("raw"))


@register(f"{chain(1)} select round(nn, 6) as nn, round(oo, 6) as oo, round(no, 6) as no, round(scale, 6) as scale from st0")
def fused_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    *_, driver, _ = run_steps(spark, sf_dir, 1)
    t = driver.trace[-1]
    return spark.createDataFrame([(t["nn"], t["oo"], t["no"], t["scale"])], "nn double, oo double, no double, scale double").select(*[F.round(c, 6).alias(c) for c in ("nn", "oo", "no", "scale")])


@register(f"{chain(1)} select id, c as j, round(v, 6) + 0.0 as f from f1")
def scaled_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, *_ = run_steps(spark, sf_dir, 1)
    return entries(rows, "f", "j", "v").select("id", F.col("j").cast("long"), r6(F.col("v")).alias("f"))


@register(f"{chain(1)} select round((select v from mv0), 6) as by_sums, round(sqrt(sum((a.v - b.v) * (a.v - b.v)) / {K}), 6) as direct from f1 a join f0 b on a.id = b.id and a.c = b.c")
def movement_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative movement from the three sums, and from both factors themselves."""
    before, *_ = run_steps(spark, sf_dir, 0)
    after, _, driver, _ = run_steps(spark, sf_dir, 1)
    both = after.select("id", "f").join(before.select("id", F.col("f").alias("g")), "id")
    direct = both.agg(F.sqrt(F.sum(vectors.sqdist(F.col("f"), F.col("g"))) / K).alias("direct"))
    return direct.select(F.round(F.lit(driver.trace[-1]["move"]), 6).alias("by_sums"), F.round("direct", 6).alias("direct"))


@register(f"{chain(3)} select id, round(v, 9) + 0.0 as dual from dual2")
def dual_after_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dual after two steps; it is added where the third sweep starts."""
    rows, *_ = run_steps(spark, sf_dir, 3)
    return rows.select("id", r6(F.col("dual"), 9).alias("dual"))


@register(f"{chain(1)} select round(sqrt(sum(v * v) / (select n from cnt)), 6) as feas from resid1")
def feasibility(spark: SparkSession, sf_dir: str) -> DataFrame:
    *_, driver, _ = run_steps(spark, sf_dir, 1)
    return spark.createDataFrame([(round(driver.trace[-1]["feas"], 6),)], "feas double")


def _trace_sql(steps: int) -> str:
    rows = [f"select {t + 1}::BIGINT as iter, round((select v from mv{t}), 6) as move, round((select sqrt(sum(v * v) / (select n from cnt)) from resid{t + 1}), 6) as feas, round((select scale from st{t}), 6) as scale" for t in range(steps)]
    return chain(steps) + " " + " union all ".join(rows)


@register(_trace_sql(3))
def three_step_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    *_, driver, _ = run_steps(spark, sf_dir, 3)
    return spark.createDataFrame([(t["iter"], t["move"], t["feas"], t["scale"]) for t in driver.trace], "iter long, move double, feas double, scale double").select("iter", *[F.round(c, 6).alias(c) for c in ("move", "feas", "scale")])


@register(f"{chain(1)} select round(-sum(v * v), 6) as objective from (select z.j, f.c, sum(z.v * f.v) as v from z join f1 f on f.id = z.id group by z.j, f.c)")
def objective_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    *_, driver, _ = run_steps(spark, sf_dir, 1)
    return spark.createDataFrame([(round(driver.trace[-1]["objective"], 6),)], "objective double")


@register(f"""{chain(1)} select round(-(select sum(v * v) from pull0) + (select sum(d.v * r.v) from dual0 d join resid0 r on r.id = d.id)
+ 0.5 * {CFG.penalty} / (select n from cnt) * (select sum(v * v) from resid0), 6) as lagrangian""")
def lagrangian_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factorclust.operators.checks import lagrangian

    rows, _, driver, (sums, _, stats) = run_steps(spark, sf_dir, 0)
    return lagrangian(rows, stats["n"], CFG.penalty).select(F.round("lagrangian", 6).alias("lagrangian"))


@register(f"{chain(1)} select f.id, f.c as j, round(-2 * p.v + e.v * s.v + h.v, 6) + 0.0 as gradient from f0 f join prod0 p on p.id = f.id and p.c = f.c join eff0 e on e.id = f.id join colsum0 s on s.c = f.c join shift0 h on h.c = f.c")
def gradient_entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factorclust.operators.checks import gradient_rows

    rows, _, _, (_, _, stats) = run_steps(spark, sf_dir, 0)
    return entries(gradient_rows(rows, stats["n"], CFG.penalty, R), "gradient", "j", "v").select("id", F.col("j").cast("long"), r6(F.col("v")).alias("gradient"))


@register("select 'breakdown' as status, 1::BIGINT as good_rows")
def breakdown_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the uniform start have too large sums for K = 10, and a long step clamps all entries: reported, with the factor left at its last good value."""
    fit = solver.fit_distributed(from_embeddings(spark, sf_dir).select("id", "x"), Config(k=10, rank=10, step=1e9, ascend=False, max_iter=5))
    norm2 = fit.factor().agg(F.sum(vectors.norm2(F.col("f")))).first()[0]
    return spark.createDataFrame([(fit.status, int(abs(norm2 - 10) < 1e-9))], "status string, good_rows long")
