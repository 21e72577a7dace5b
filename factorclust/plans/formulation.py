"""Queries of the formulation, the normalisation, the measures and the cost model."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import theory
from factorclust.operators import metrics, normalize, partition
from factorclust.plans.pieces import r6
from factorclust.registry import register
from factorclust.sources.points import from_embeddings, half_bands, planted
from factorclust.sources.tables import read_table

#: A portable assignment for the measures: id mod K.
K = 7
LONG = "e as (select vec_id as id, label, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j))"


def modulo(points: DataFrame, k: int = K) -> DataFrame:
    return points.withColumn("cluster", (F.col("id") % k).cast("int"))


@register(f"with {LONG}, m as (select label, j, avg(v) as m from e group by label, j) select e.label as truth, count(*) // 64 as size, round(sum((v - m) * (v - m)), 6) as wcss from e join m on m.label = e.label and m.j = e.j group by e.label")
def wcss_two_pass(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.wcss(from_embeddings(spark, sf_dir), "truth").select("truth", "size", r6(F.col("wcss")).alias("wcss"))


@register(f"with {LONG}, s as (select label, j, sum(v) as s, sum(v * v) as q, count(*) as n from e group by label, j) select round(sum(q), 6) as energy, round(sum(s * s / n), 6) as explained, round(sum(q) - sum(s * s / n), 6) as wcss from s")
def wcss_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = partition.wcss_by_energy(from_embeddings(spark, sf_dir), "truth")
    return got.select(*[r6(F.col(c)).alias(c) for c in ("energy", "explained", "wcss")])


@register(f"select vec_id as id, (vec_id % {K})::INTEGER as cluster, round(1 / sqrt(count(*) over (partition by vec_id % {K})), 9) as weight from embeddings")
def assignment_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.assignment_factor(modulo(from_embeddings(spark, sf_dir)).select("id", "cluster")).select("id", "cluster", F.round("weight", 9).alias("weight"))


@register(f"with s as (select vec_id % {K} as c, count(*) as n from embeddings group by 1) select a.vec_id as i, round(sum(1.0 / n), 9) as row_sum from embeddings a join embeddings b on a.vec_id % {K} = b.vec_id % {K} join s on s.c = a.vec_id % {K} group by a.vec_id")
def membership_rowsum(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = partition.assignment_factor(modulo(from_embeddings(spark, sf_dir)).select("id", "cluster"))
    return partition.membership_rows(f).select("i", F.round("row_sum", 9).alias("row_sum"))


@register(f"select * from (values ('nonnegative', true), ('trace', true), ('row_sums', true), ('projection', true)) t(property, ok)")
def membership_properties(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = partition.assignment_factor(modulo(from_embeddings(spark, sf_dir)).select("id", "cluster"))
    return partition.check_membership(f, K).select("property", "ok")


@register(f"with {LONG}, s as (select id % {K} as c, j, sum(v) as s, count(*) as n from e group by 1, j) select round(sum(s * s / n), 6) as inner_product from s")
def membership_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The inner product of the points' inner products with the membership matrix, from its factor."""
    p = modulo(from_embeddings(spark, sf_dir))
    f = partition.assignment_factor(p.select("id", "cluster"))
    return partition.membership_product(f, p).select(F.round("inner_product", 6).alias("inner_product"))


_SHAPES = "(values " + ", ".join(f"({i}, {d}, {k}, {r}, {s})" for i, (_, d, k, r, s) in enumerate(theory.SETTINGS, 1)) + ") s(i, d, k, r, seeds)"
#: The published shapes, each for as many points as lineitem has rows of one line number.
_GRID = f"(select c.n, s.d, s.k, s.r, s.seeds from (select l_linenumber as i, count(l_quantity) as n from lineitem group by 1) c join {_SHAPES} on s.i = c.i) t"


def settings(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_quantity"]).groupBy(F.col("l_linenumber").cast("int").alias("i")).agg(F.count("l_quantity").alias("n"))
    shapes = spark.createDataFrame([(i, *s[1:]) for i, s in enumerate(theory.SETTINGS, 1)], "i int, d long, k long, r long, seeds long")
    return lines.join(F.broadcast(shapes), "i").select("n", "d", "k", "r", "seeds")


def setting_rows(spark: SparkSession, sf_dir: str) -> list[tuple[int, int, int, int, int]]:
    return [tuple(s) for s in settings(spark, sf_dir).collect()]  # six rows


@register(f"select n::BIGINT as n, d::BIGINT as d, k::BIGINT as k, round(4 * (1 + sqrt(1 + k * d / (n * ln(n)))) * ln(n), 6) as squared, round(sqrt(4 * (1 + sqrt(1 + k * d / (n * ln(n)))) * ln(n)), 6) as threshold from (select distinct n::DOUBLE as n, d::DOUBLE as d, k::DOUBLE as k from {_GRID})")
def cnr_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    sq = theory.cnr_squared_col(F.col("n").cast("double"), F.col("d").cast("double"), F.col("k").cast("double"))
    return settings(spark, sf_dir).select("n", "d", "k").distinct().select("n", "d", "k", F.round(sq, 6).alias("squared"), F.round(F.sqrt(sq), 6).alias("threshold"))


@register(f"select n::BIGINT as n, k::BIGINT as k, round(ln(n) / ln(ln(n)), 6) as lim, k <= ln(n) / ln(ln(n)) as within from (select distinct n::DOUBLE as n, k from {_GRID})")
def regime_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    limit = F.ln("n") / F.ln(F.ln("n"))
    return settings(spark, sf_dir).select("n", "k").distinct().select("n", "k", F.round(limit, 6).alias("lim"), (F.col("k") <= limit).alias("within"))


_SEP = f"with {LONG}, m as (select label, j, avg(v) as m, count(*) as n from e group by label, j), w as (select sum((v - m) * (v - m)) as w from e join m on m.label = e.label and m.j = e.j), p as (select a.label as a, b.label as b, sqrt(sum((a.m - b.m) * (a.m - b.m))) as far from m a join m b on a.j = b.j and a.label < b.label group by a.label, b.label), c as (select count(*) as n, count(distinct label) as k from embeddings)"


@register(f"{_SEP} select round(min(far), 6) as delta, round(sqrt((select w from w) / (((select n from c) - (select k from c)) * 64)), 6) as sigma from p")
def center_separation(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = partition.separation(from_embeddings(spark, sf_dir))
    return s.select(F.round("delta", 6).alias("delta"), F.round("sigma", 6).alias("sigma"))


@register("select * from (values (0.5, 'impossible'), (1.0, 'edge'), (2.0, 'recoverable')) t(gamma, verdict)".replace("0.5", "0.5::DOUBLE").replace("1.0,", "1.0::DOUBLE,").replace("2.0,", "2.0::DOUBLE,"))
def recovery_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The verdict on the measured separation of planted data, within a tenth of the threshold."""
    rows = []
    for gamma in (0.5, 1.0, 2.0):
        p = planted(spark, sf_dir, gamma)
        s, n = partition.separation(p).first(), p.count()
        ratio = s.delta / s.sigma / theory.cnr_threshold(n, 64, 10)
        rows.append((gamma, theory.recovery_verdict(ratio, 0.25)))
    return spark.createDataFrame(rows, "gamma double, verdict string")


@register("select k::BIGINT as k, beta::DOUBLE as beta, dual, round(2 + 2 * dual + beta::DOUBLE * (6 * k + 2), 6)::DOUBLE as bound from (select unnest([1, 10, 20, 100]) as k), (select unnest([0.1, 1.0, 10.0]) as beta), (select l_linenumber, max(l_extendedprice * l_discount)::DOUBLE as dual from lineitem group by l_linenumber)")
def smoothness_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bound for the largest discount in money of each line number as the multiplier."""
    lines = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_extendedprice", "l_discount"]).groupBy("l_linenumber").agg(F.max(F.col("l_extendedprice") * F.col("l_discount")).cast("double").alias("y"))
    duals = [r.y for r in lines.select("y").collect()]  # one a line number
    rows = [(k, b, y, round(theory.smoothness_bound(y, b, k), 6)) for k in (1, 10, 20, 100) for b in (0.1, 1.0, 10.0) for y in duals]
    return spark.createDataFrame(rows, "k long, beta double, dual double, bound double")


# --- normalisation ----------------------------------------------------------------------------------------------


@register(f"with {LONG} select j, round(avg(v), 9) + 0.0 as mean from e group by j")
def column_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).select(F.posexplode("x").alias("j", "v")).groupBy(F.col("j").cast("long").alias("j")).agg(r6(F.avg("v"), 9).alias("mean"))


@register(f"with {LONG}, m as (select j, avg(v) as m from e group by j) select round(sum((v - m) * (v - m)), 6) as energy from e join m using (j)")
def centered_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = from_embeddings(spark, sf_dir)
    mean = normalize.column_stats(p)["mean"]
    return partition.total_energy(normalize.center(p, mean)).select(F.round("energy", 6).alias("energy"))


@register(f"with {LONG}, m as (select j, avg(v) as m from e group by j), c as (select id, j, v - m as v from e join m using (j)) select a.j as i, b.j as j, round(sum(a.v * b.v), 6) + 0.0 as v from c a join c b on a.id = b.id and a.j <= b.j where b.j < 16 group by a.j, b.j")
def gram_upper(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The leading part of the second moment."""
    p = from_embeddings(spark, sf_dir)
    g = normalize.gram_matrix(p, normalize.column_stats(p)["mean"])
    rows = [(i, j, float(g[i, j])) for i in range(16) for j in range(i, 16)]
    return spark.createDataFrame(rows, "i long, j long, v double").select("i", "j", r6(F.col("v")).alias("v"))


@register(f"with {LONG}, m as (select j, avg(v) as m from e group by j), c as (select id, j, v - m as v from e join m using (j)) select a.j as i, b.j as j, round(sum(a.v * b.v), 6) + 0.0 as v from c a join c b on a.id = b.id and a.j <= b.j group by a.j, b.j")
def gram_upper_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The second moment of all columns."""
    p = from_embeddings(spark, sf_dir)
    g = normalize.gram_matrix(p, normalize.column_stats(p)["mean"])
    rows = [(i, j, float(g[i, j])) for i in range(len(g)) for j in range(i, len(g))]
    return spark.createDataFrame(rows, "i long, j long, v double").select("i", "j", r6(F.col("v")).alias("v"))


_POWER = f"with {LONG}, m as (select j, avg(v) as m from e group by j), c as materialized (select id, j, v - m as v from e join m using (j)), v0 as (select j, 1 / sqrt(64.0) as v from m)" + "".join(
    f", p{t} as materialized (select id, sum(c.v * w.v) as v from c join v{t} w using (j) group by id), w{t} as materialized (select j, sum(c.v * p.v) as v from c join p{t} p using (id) group by j), v{t + 1} as materialized (select j, v / sqrt((select sum(v * v) from w{t})) as v from w{t})" for t in range(3)
)


@register(f"{_POWER} " + " union all ".join(f"select {t + 1}::BIGINT as step, round(sqrt(sqrt(sum(v * v))), 6) as estimate from w{t}" for t in range(3)))
def power_vector_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    import numpy as np

    p = from_embeddings(spark, sf_dir).select("id", "x").persist()
    mean = normalize.column_stats(p)["mean"]
    v, rows = np.ones(64) / 8.0, []
    for t in range(3):
        w = normalize._power_step(p, mean, v)
        rows.append((t + 1, float(np.sqrt(np.linalg.norm(w)))))
        v = w / np.linalg.norm(w)
    p.unpersist()
    return spark.createDataFrame(rows, "step long, e double").select("step", F.round("e", 6).alias("estimate"))


@register("with h as (select vec_id as id, j, embedding[j + 1]::DOUBLE as v, j // 32 as half from embeddings, (select unnest(range(64)) as j)), n as (select id, half, sqrt(sum(v * v)) as n from h group by id, half) select h.id, h.j, round(h.v / n.n, 6) + 0.0 as v from h join n on n.id = h.id and n.half = h.half where h.id % 10 = 0")
def unit_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = half_bands(from_embeddings(spark, sf_dir).where("id % 10 = 0"))
    return p.select("id", F.posexplode("x").alias("j", "v")).select("id", F.col("j").cast("long"), r6(F.col("v")).alias("v"))


@register("with h as (select vec_id as id, j, embedding[j + 1]::DOUBLE as v, j // 32 as half from embeddings, (select unnest(range(64)) as j)), n as (select id, half, sqrt(sum(v * v)) as n from h group by id, half) select h.id, h.j, round(h.v / n.n, 6) + 0.0 as v from h join n on n.id = h.id and n.half = h.half")
def unit_bands_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = half_bands(from_embeddings(spark, sf_dir))
    return p.select("id", F.posexplode("x").alias("j", "v")).select("id", F.col("j").cast("long"), r6(F.col("v")).alias("v"))


# --- measures ---------------------------------------------------------------------------------------------------

_TABLE = f"t as (select (vec_id % {K})::INTEGER as cluster, label, count(*) as n from embeddings group by 1, 2)"


def table_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = from_embeddings(spark, sf_dir)
    return metrics.contingency(modulo(e).select("id", "cluster"), e.select("id", F.col("truth").alias("label")))


@register(f"with {_TABLE} select * from t")
def contingency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table_of(spark, sf_dir)


@register(f"with {_TABLE} select cluster, label, sum(n)::BIGINT as n from t group by cube (cluster, label)")
def contingency_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table_of(spark, sf_dir).cube("cluster", "label").agg(F.sum("n").alias("n"))


_C2 = "sum(n * (n - 1) / 2.0)"
_ARI = f"with {_TABLE}, b as (select {_C2} as x, sum(n)::DOUBLE as total from t), r as (select {_C2} as x from (select sum(n) as n from t group by cluster)), c as (select {_C2} as x from (select sum(n) as n from t group by label))"


@register(f"{_ARI} select round((b.x - r.x * c.x / (total * (total - 1) / 2)) / ((r.x + c.x) / 2 - r.x * c.x / (total * (total - 1) / 2)), 9) + 0.0 as ari from b, r, c")
def ari_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ari(table_of(spark, sf_dir)).select(r6(F.col("ari"), 9).alias("ari"))


_H = f"with {_TABLE}, tot as (select sum(n)::DOUBLE as z from t), a as (select -sum(p * ln(p)) as h from (select sum(n) / (select z from tot) as p from t group by cluster)), b as (select -sum(p * ln(p)) as h from (select sum(n) / (select z from tot) as p from t group by label)), j as (select -sum(p * ln(p)) as h from (select n / (select z from tot) as p from t))"
_NORMS = {"arithmetic": "(a.h + b.h) / 2", "geometric": "sqrt(a.h * b.h)", "min": "least(a.h, b.h)", "max": "greatest(a.h, b.h)", "joint": "j.h"}


@register(f"{_H} select round((a.h + b.h - j.h) / ((a.h + b.h) / 2), 9) as nmi from a, b, j")
def nmi_arith(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.nmi(table_of(spark, sf_dir)).select(F.round("nmi", 9).alias("nmi"))


@register(f"{_H} " + " union all ".join(f"select '{k}' as norm, round((a.h + b.h - j.h) / ({v}), 9) as nmi from a, b, j" for k, v in _NORMS.items()))
def nmi_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table_of(spark, sf_dir)
    each = [metrics.nmi(t, k).select(F.lit(k).alias("norm"), F.round("nmi", 9).alias("nmi")) for k in _NORMS]
    out = each[0]
    for e in each[1:]:
        out = out.unionByName(e)
    return out


@register(f"{_H} select round((a.h + b.h - j.h) / b.h, 9) as homogeneity, round((a.h + b.h - j.h) / a.h, 9) as completeness, round(2 * (a.h + b.h - j.h) / (a.h + b.h), 9) as v from a, b, j")
def v_measure(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.v_measure(table_of(spark, sf_dir)).select(*[F.round(c, 9).alias(c) for c in ("homogeneity", "completeness", "v")])


@register(f"with {_TABLE} select round(sum(m) / sum(s), 9) as purity from (select max(n) as m, sum(n) as s from t group by cluster)")
def purity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.purity(table_of(spark, sf_dir)).select(F.round("purity", 9).alias("purity"))


@register(f"with {_TABLE} select round(1 - sum(m) / sum(s), 9) as error from (select max(n) as m, sum(n) as s from t group by cluster)")
def misclustering_majority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.purity(table_of(spark, sf_dir)).select(F.round(1 - F.col("purity"), 9).alias("error"))


def _permutations(k: int) -> str:
    """Best one-to-one match over all permutations of k labels."""
    from_ = ", ".join(f"(select unnest(range({k})) as p{i}) q{i}" for i in range(k))
    apart = " and ".join(f"p{i} <> p{j}" for i in range(k) for j in range(i)) or "true"
    gain = " + ".join(f"coalesce((select n from t where c = {i} and l = p{i}), 0)" for i in range(k))
    return f"select max({gain}) as best from {from_} where {apart}"


@register(f"with t as (select vec_id % 4 as c, label % 4 as l, count(*) as n from embeddings group by 1, 2) select round(1 - best / (select count(*) from embeddings)::DOUBLE, 9) as error from ({_permutations(4)})")
def misclustering_matched(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = from_embeddings(spark, sf_dir)
    t = e.groupBy((F.col("id") % 4).alias("cluster"), (F.col("truth") % 4).alias("label")).agg(F.count(F.lit(1)).alias("n"))
    return spark.createDataFrame([(round(metrics.misclustering(t), 9),)], "error double")


@register("select count(*) as classes, max(n) as largest, min(n) as smallest, sum(n)::BIGINT as total from (select count(*) as n from documents group by lang)")
def label_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.label_profile(read_table(spark, sf_dir, "documents", ["lang"]), "lang")


@register("select o_orderpriority, round(quantile_cont(o_totalprice, 0.25), 6) as q1, round(median(o_totalprice), 6) as median, round(quantile_cont(o_totalprice, 0.75), 6) as q3, round(avg(o_totalprice), 4) as mean, min(o_totalprice) as low, max(o_totalprice) as high, count(*) as runs from orders group by 1")
def seed_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The summary of results over runs, on a column of the tables."""
    s = metrics.summarise(read_table(spark, sf_dir, "orders", ["o_orderpriority", "o_totalprice"]), ["o_orderpriority"], "o_totalprice")
    return s.select("o_orderpriority", *[F.round(c, 6).alias(c) for c in ("q1", "median", "q3")], F.round("mean", 4).alias("mean"), "low", "high", "runs")


# --- costs ------------------------------------------------------------------------------------------------------

_TILE = "ceil(n / 128.0) * ceil(r / 64.0)"


def _grid(spark: SparkSession, sf_dir: str, *columns) -> DataFrame:
    return settings(spark, sf_dir).select("n", "d", "k", "r", *columns)


_HEAD = "select n::BIGINT as n, d::BIGINT as d, k::BIGINT as k, r::BIGINT as r"


@register(f"{_HEAD}, (4 * n::BIGINT * d * r)::BIGINT as flops from {_GRID}")
def flops_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(n, d, k, r, theory.flops(n, d, r)) for n, d, k, r, _ in setting_rows(spark, sf_dir)], "n long, d long, k long, r long, flops long")


@register(f"{_HEAD}, ({_TILE})::BIGINT as tiles, (24 * {_TILE})::BIGINT as bytes from {_GRID}")
def tile_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    n_tiles = F.ceil(F.col("n") / 128) * F.ceil(F.col("r") / 64)
    return _grid(spark, sf_dir, n_tiles.alias("tiles"), (24 * n_tiles).alias("bytes"))


@register(f"{_HEAD}, (4 * (n::BIGINT * d + n::BIGINT * r + d * r + 4 * n::BIGINT + 2 * r) + 24 * ({_TILE} + 1))::BIGINT as bytes from {_GRID}")
def buffer_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(n, d, k, r, theory.buffer_bytes(n, d, r, theory.tiles(n, r, 128, 64))) for n, d, k, r, _ in setting_rows(spark, sf_dir)], "n long, d long, k long, r long, bytes long")


@register(f"{_HEAD}, (8 * n::BIGINT * r)::BIGINT as saved from {_GRID}")
def saved_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grid(spark, sf_dir, (8 * F.col("n") * F.col("r")).alias("saved"))


#: Bytes of the accelerator that the published runs used for each row of their largest data set; as many for each of the largest n here.
DEVICE_A_ROW = 141_000_000_000 // 200_000_000


@register(f"with b as ({_HEAD}, (4 * (n::BIGINT * d + n::BIGINT * r + d * r + 4 * n::BIGINT + 2 * r) + 24 * ({_TILE} + 1))::BIGINT as one from {_GRID}), m as (select {DEVICE_A_ROW} * max(n) as device from b) select n, d, k, r, one <= device as one_buffer, one + 8 * n * r <= device as three_buffers from b, m")
def fits_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where a single factor buffer decides whether a setting fits the device."""
    of = setting_rows(spark, sf_dir)
    device = DEVICE_A_ROW * max((s[0] for s in of), default=0)
    rows = [(n, d, k, r, theory.fits(n, d, r, t := theory.tiles(n, r, 128, 64), device), theory.fits(n, d, r, t, device, 3)) for n, d, k, r, _ in of]
    return spark.createDataFrame(rows, "n long, d long, k long, r long, one_buffer boolean, three_buffers boolean")


