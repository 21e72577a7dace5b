"""Relational operators around the methods: scans, joins, aggregates, windows, sorts, sets, subqueries, reshaping.

Where Spark SQL and DuckDB read the same text, one text is query and oracle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from factorclust.functions import portable, vectors
from factorclust.operators import lloyd
from factorclust.plans import workloads
from factorclust.plans.pieces import r6
from factorclust.registry import register, register_sql
from factorclust.sources.points import from_embeddings, from_json
from factorclust.sources.tables import read_table, split_valid

# --- scans and projections --------------------------------------------------------------------------------------

register_sql("rel_project_features", "select l_orderkey, l_linenumber, cast(l_quantity as double) as f1, cast(l_extendedprice as double) as f2, cast(l_discount as double) as f3, cast(l_tax as double) as f4 from {lineitem}", ("lineitem",))
register_sql("rel_filter_range", "select l_orderkey, l_partkey, l_quantity from {lineitem} where l_shipdate >= timestamp '1996-01-01 00:00:00' and l_quantity between 10 and 20 and l_returnflag in ('A', 'R')", ("lineitem",))
register_sql("rel_scan_pruned", "select o_orderkey, o_totalprice from {orders} where o_totalprice > 200000 and o_orderstatus = 'F'", ("orders",))
register_sql("rel_filter_like", "select p_partkey, p_name from {part} where p_name like '%a%' and p_size < 20", ("part",))


@register("select vec_id as id, len(embedding)::INTEGER as width from embeddings where embedding is not null and len(embedding) = 64")
def rel_filter_valid(spark: SparkSession, sf_dir: str) -> DataFrame:
    good, _ = split_valid(from_embeddings(spark, sf_dir), 64)
    return good.select("id", F.size("x").alias("width"))


# --- joins ------------------------------------------------------------------------------------------------------


@register("select vec_id as id, (vec_id % 10)::INTEGER as cluster, label from embeddings")
def join_assign_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = from_embeddings(spark, sf_dir)
    a = e.select("id", (F.col("id") % 10).cast("int").alias("cluster"))
    return a.join(e.select("id", F.col("truth").alias("label")), "id")


register_sql("join_left_labels", "select d.doc_id, d.lang, l.quality from {documents} d left join {labels} l on d.doc_id = l.doc_id", ("documents", "labels"))
register_sql("join_full_labels", "select d.doc_id as a, l.doc_id as b from (select * from {documents} where doc_id % 2 = 0) d full join (select * from {labels} where doc_id % 3 = 0) l on d.doc_id = l.doc_id", ("documents", "labels"))
register_sql("join_right_labels", "select d.doc_id as a, l.doc_id as b, l.toxic from (select * from {documents} where doc_id % 2 = 0) d right join {labels} l on d.doc_id = l.doc_id", ("documents", "labels"))
register_sql("join_full_labels_whole", "select d.doc_id as a, l.doc_id as b from {documents} d full join {labels} l on d.doc_id = l.doc_id", ("documents", "labels"))
register_sql("join_right_labels_whole", "select d.doc_id as a, l.doc_id as b, l.toxic from {documents} d right join {labels} l on d.doc_id = l.doc_id", ("documents", "labels"))
register_sql("join_semi_labelled", "select doc_id, n_chars from {documents} d where exists (select 1 from {labels} l where l.doc_id = d.doc_id)", ("documents", "labels"))
register_sql("join_anti_unlabelled", "select doc_id, n_chars from {documents} d where not exists (select 1 from {labels} l where l.doc_id = d.doc_id)", ("documents", "labels"))


@register("select r_name, n_name, count(*) as customers, round(sum(c_acctbal), 4) as balance from region join nation on n_regionkey = r_regionkey join customer on c_nationkey = n_nationkey group by r_name, n_name")
def join_broadcast_dims(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region and nation have 5 and 25 rows by definition, so both may be broadcast."""
    r, n = read_table(spark, sf_dir, "region", ["r_regionkey", "r_name"]), read_table(spark, sf_dir, "nation", ["n_nationkey", "n_name", "n_regionkey"])
    dims = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    c = read_table(spark, sf_dir, "customer", ["c_nationkey", "c_acctbal"])
    return c.join(F.broadcast(dims), c.c_nationkey == dims.n_nationkey).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 4).alias("balance"))


_FACT = "select o_orderpriority, count(*) as lines, round(sum(l_quantity), 4) as quantity from orders join lineitem on l_orderkey = o_orderkey group by o_orderpriority"


def _fact(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    o, li = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"]), read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity"])
    return li.join(o.hint(how), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_quantity"), 4).alias("quantity"))


@register(_FACT)
def join_merge_fact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fact(spark, sf_dir, "merge")


@register(_FACT)
def join_shuffle_hash_fact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fact(spark, sf_dir, "shuffle_hash")


_E = "e as (select vec_id as id, label, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j)), m as (select label, j, avg(v) as v from e group by label, j)"


@register(f"with {_E} select a.label as k, b.label as l, round(sqrt(sum((a.v - b.v) * (a.v - b.v))), 6) as far from m a join m b on a.j = b.j and a.label < b.label group by a.label, b.label")
def join_theta_centers(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factorclust.operators.partition import means

    m = means(from_embeddings(spark, sf_dir), "truth").select("truth", "mean")
    pair = m.alias("a").join(m.alias("b"), F.col("a.truth") < F.col("b.truth"))
    return pair.select(F.col("a.truth").alias("k"), F.col("b.truth").alias("l"), F.round(F.sqrt(vectors.sqdist(F.col("a.mean"), F.col("b.mean"))), 6).alias("far"))


@register(f"with {_E}, d as (select e.id, m.label as c, round(sum((e.v - m.v) * (e.v - m.v)), 9) as d from e join m using (j) group by e.id, m.label) select id, min_by(c, d) as cluster, round(min(d), 6) as distance2 from d group by id")
def join_cross_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points by K centroids in the row: an array of the K centres takes the place of a cross join."""
    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    m = means(p, "truth").agg(F.array_sort(F.collect_list(F.struct("truth", "mean"))).alias("c"))  # K entries
    dist = F.transform("c", lambda c: F.struct(F.round(vectors.sqdist(F.col("x"), c["mean"]), 9).alias("d"), c["truth"].alias("cluster")))
    return p.join(F.broadcast(m)).select("id", F.array_min(dist).alias("best")).select("id", F.col("best.cluster").alias("cluster"), F.round("best.d", 6).alias("distance2"))


@register("select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_partkey < b.p_partkey and abs(a.p_retailprice - b.p_retailprice) <= 0.05 and a.p_type = b.p_type")
def join_range_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs within a band: each row goes to its own bucket and its neighbours, then an equi join and the exact test."""
    band = 0.05
    p = read_table(spark, sf_dir, "part", ["p_partkey", "p_retailprice", "p_type"]).withColumn("bucket", F.floor(F.col("p_retailprice") / band))
    a = p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("pa"), "p_type", F.explode(F.array(*[F.col("bucket") + i for i in (-1, 0, 1)])).alias("bucket"))
    b = p.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("pb"), "p_type", "bucket")
    return a.join(b, ["p_type", "bucket"]).where((F.col("a") < F.col("b")) & (F.abs(F.col("pa") - F.col("pb")) <= band)).select("a", "b")


@register("select a.event_id as first_id, b.event_id as second_id from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def join_interval_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_id", "user_id", "ts"])
    hour = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000)
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(hour, hour + 1)).alias("hour"))
    b = e.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("t2"), hour.alias("hour"))
    return a.join(b, ["user_id", "hour"]).where("t2 > t1 and t2 <= t1 + interval 1 hour").select("first_id", "second_id")


@register("with v as (select user_id, ts, event_id as version from events where event_type = 'purchase') select e.event_id, v.version from (select * from events where event_type <> 'purchase') e asof left join v on e.user_id = v.user_id and e.ts >= v.ts")
def join_asof_version(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last version at or before each event: both sides in one stream per key, last value carried on."""
    e = read_table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"])
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("is_version")).rowsBetween(Window.unboundedPreceding, 0)
    marked = e.withColumn("is_version", (F.col("event_type") == "purchase").cast("int"))
    return marked.withColumn("version", F.last(F.when(F.col("is_version") == 1, F.col("event_id")), ignorenulls=True).over(w)).where("is_version = 0").select("event_id", "version")


# --- aggregates -------------------------------------------------------------------------------------------------

register_sql("agg_hash_partial_final", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 4) as quantity, round(avg(l_discount), 6) as discount from {lineitem} group by l_returnflag, l_linestatus", ("lineitem",))
register_sql("agg_sort", "select l_returnflag, max(l_linestatus) as last_status, min(l_shipdate) as first_ship from {lineitem} group by l_returnflag", ("lineitem",))
register_sql("agg_distinct", "select event_type, count(distinct user_id) as users from {events} group by event_type", ("events",))
register_sql("agg_moments", "select l_returnflag, round(avg(l_quantity), 6) as mean, round(var_samp(l_quantity), 6) as variance, round(corr(l_quantity, l_extendedprice), 6) as r, round(covar_pop(l_quantity, l_extendedprice), 4) as cov from {lineitem} group by l_returnflag", ("lineitem",))
register_sql("agg_grouping_sets", "select o_orderstatus, o_orderpriority, count(*) as n from {orders} group by grouping sets ((o_orderstatus), (o_orderpriority), ())", ("orders",))
register_sql("agg_rollup", "select o_orderstatus, o_orderpriority, count(*) as n from {orders} group by rollup (o_orderstatus, o_orderpriority)", ("orders",))
register_sql("agg_filter_having", "select user_id, count(*) filter (where event_type = 'purchase') as purchases from {events} group by user_id having count(*) > 5", ("events",))


@register("select event_type, round(quantile_cont(value, 0.25), 6) as q1, round(quantile_cont(value, 0.5), 6) as q2, round(quantile_cont(value, 0.75), 6) as q3 from events group by event_type")
def agg_percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_type", "value"])
    return e.groupBy("event_type").agg(*[F.round(F.percentile("value", F.lit(p)), 6).alias(n) for n, p in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))])


@register()
def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events", ["event_type", "user_id"]).groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.approx_percentile("user_id", F.lit(0.5)).alias("mid"))


@register(f"with {_E} select label, j, round(sum(v), 6) + 0.0 as s from e group by label, j")
def agg_vector_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spark's own vector aggregate: partial and final."""
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    s = from_embeddings(spark, sf_dir).groupBy(F.col("truth").alias("label")).agg(Summarizer.sum(array_to_vector(F.col("x"))).alias("s"))
    return s.select("label", F.posexplode(vector_to_array("s")).alias("j", "s")).select("label", F.col("j").cast("long"), r6(F.col("s")).alias("s"))


@register(f"with {_E} select label, j, round(v, 9) + 0.0 as m from m")
def agg_vector_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).select(F.col("truth").alias("label"), F.posexplode("x").alias("j", "v")).groupBy("label", F.col("j").cast("long").alias("j")).agg(r6(F.avg("v"), 9).alias("m"))


@register("select (vec_id % 3)::INTEGER as cluster, count(*) filter (where label = 0) as c0, count(*) filter (where label = 1) as c1, count(*) filter (where label = 2) as c2 from embeddings where label < 3 group by 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = from_embeddings(spark, sf_dir).where("truth < 3").select((F.col("id") % 3).cast("int").alias("cluster"), "truth")
    return e.groupBy("cluster").pivot("truth", [0, 1, 2]).count().select("cluster", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"c{i}") for i in range(3)])


@register("select label, min_by(vec_id, round(embedding[1], 9) * 1000000 + vec_id / 1e9) as low, max_by(vec_id, round(embedding[1], 9) * 1000000 + vec_id / 1e9) as high from embeddings group by label".replace("round(embedding[1], 9)", "round(embedding[1]::DOUBLE, 9)"))
def agg_minmax_by(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = F.round(F.col("x")[0], 9) * 1000000 + F.col("id") / 1e9
    return from_embeddings(spark, sf_dir).groupBy(F.col("truth").alias("label")).agg(F.min_by("id", order).alias("low"), F.max_by("id", order).alias("high"))


# --- windows ----------------------------------------------------------------------------------------------------

register_sql("win_rank_family", "select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd from {orders} window w as (partition by o_custkey order by o_totalprice, o_orderkey)", ("orders",), "select o_orderkey, (row_number() over w)::INTEGER as rn, (rank() over w)::INTEGER as rk, (dense_rank() over w)::INTEGER as dr, (ntile(4) over w)::INTEGER as nt, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey)")
register_sql("win_lag_lead_trace", "select event_id, lag(value) over (partition by user_id order by ts, event_id) as before, lead(value, 2) over (partition by user_id order by ts, event_id) as after from {events}", ("events",))
register_sql("win_running_sum", "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row), 4) as total from {orders}", ("orders",))
register_sql("win_moving_mean", "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 3 preceding and current row), 6) as smooth from {events}", ("events",))
register_sql("win_first_last_nth", "select event_id, first_value(event_id) over w as f, last_value(event_id) over w as l, nth_value(event_id, 2) over w as s from {events} window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)", ("events",))
register_sql("win_cluster_size", "select vec_id, label, count(*) over (partition by label) as size from {embeddings}", ("embeddings",))


@register("select event_id, round(sum(value) over (partition by user_id order by ts range between interval 1 day preceding and current row), 6) as day from events")
def win_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "value"])
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 6).alias("day"))


# --- order, limits, sets ----------------------------------------------------------------------------------------

register_sql("sort_multi", "select o_orderkey, o_orderstatus, o_totalprice from {orders} order by o_orderstatus, o_totalprice desc, o_orderkey", ("orders",))
register_sql("limit_offset", "select o_orderkey, o_totalprice from {orders} order by o_totalprice desc, o_orderkey limit 20 offset 40", ("orders",))
register_sql("topk_global", "select event_id, value from {events} order by value desc, event_id limit 25", ("events",))
register_sql("topk_per_cluster", "select user_id, event_id, value from (select *, row_number() over (partition by user_id order by value desc, event_id) as rn from {events}) where rn <= 3", ("events",), "select user_id, event_id, value from (select *, row_number() over (partition by user_id order by value desc, event_id) as rn from events) where rn <= 3")
for _name, _op in (("set_union_all", "union all"), ("set_union", "union"), ("set_intersect", "intersect"), ("set_intersect_all", "intersect all"), ("set_except", "except"), ("set_except_all", "except all")):
    register_sql(_name, f"select l_returnflag, l_suppkey from {{lineitem}} where l_quantity < 10 {_op} select l_returnflag, l_suppkey from {{lineitem}} where l_quantity >= 40", ("lineitem",))

# --- sampling, reshaping, subqueries ----------------------------------------------------------------------------


@register(f"select vec_id as id from embeddings where {portable.mix_sql('vec_id', 0, 9)} % 4 = 0")
def sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quarter of the rows, the same ones on any partitioning (a sampling operator)."""
    return from_embeddings(spark, sf_dir).where(F.pmod(portable.mix(F.col("id"), 0, 9), F.lit(4)) == 0).select("id")


@register()
def sample_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).sampleBy("truth", {i: 0.1 * (i + 1) / 2 for i in range(10)}, seed=3).groupBy("truth").count()


@register("select vec_id as id, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j) where vec_id < 50")
def reshape_explode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).where("id < 50").select("id", F.posexplode("x").alias("j", "v")).withColumn("j", F.col("j").cast("long"))


@register("select vec_id as id, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j)")
def reshape_explode_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).select("id", F.posexplode("x").alias("j", "v")).withColumn("j", F.col("j").cast("long"))


@register("select label, count(*) as n, min(vec_id) as first_id, sum(vec_id)::BIGINT as ids from embeddings group by label")
def reshape_collect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of a label as a sorted array, then read back."""
    a = from_embeddings(spark, sf_dir).groupBy(F.col("truth").alias("label")).agg(F.array_sort(F.collect_list("id")).alias("ids"))
    return a.select("label", F.size("ids").cast("long").alias("n"), F.col("ids")[0].alias("first_id"), F.aggregate("ids", F.lit(0).cast("long"), lambda s, x: s + x).alias("ids"))


@register("select o_orderkey, name, value from orders unpivot (value for name in (o_totalprice, o_custkey))".replace("from orders", "from (select o_orderkey, o_totalprice, o_custkey::DOUBLE as o_custkey from orders)"))
def reshape_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice", "o_custkey"]).withColumn("o_custkey", F.col("o_custkey").cast("double"))
    return o.unpivot(["o_orderkey"], ["o_totalprice", "o_custkey"], "name", "value")


@register("select count(*) as rows, round(sum(embedding[1]::DOUBLE), 6) + 0.0 as s from embeddings")
def reshape_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows to tiles and back."""
    from factorclust.operators import solver
    from factorclust.operators.kernel import Config
    from factorclust.plans.pieces import rows_of
    import numpy as np

    tiles = solver.build_tiles(from_embeddings(spark, sf_dir).select("id", "x"), np.zeros(64), 1.0, Config(k=2), tile_rows=100)
    return rows_of(tiles, 1.0).agg(F.count(F.lit(1)).alias("rows"), r6(F.sum(F.col("z")[0])).alias("s"))


register_sql("sub_scalar", "select o_orderkey from {orders} where o_totalprice > (select avg(o_totalprice) * 1.5 from {orders})", ("orders",))
register_sql("sub_exists", "select o_orderkey from {orders} o where exists (select 1 from {lineitem} l where l.l_orderkey = o.o_orderkey and l.l_quantity > 45)", ("orders", "lineitem"))
register_sql("sub_correlated", "select l_orderkey, l_linenumber, l_partkey from {lineitem} l where l_quantity > (select 1.4 * avg(l_quantity) from {lineitem} i where i.l_partkey = l.l_partkey)", ("lineitem",))

# --- uses of clusters -------------------------------------------------------------------------------------------


@register("with per as (select l_orderkey, sum(l_quantity) as q, sum(l_discount) as disc, count(*) as lines from lineitem group by l_orderkey), c as (select o_custkey, count(*) as orders, sum(o_totalprice) as spend, coalesce(sum(q), 0) as items, coalesce(sum(disc) / sum(lines), 0) as disc from orders left join per on l_orderkey = o_orderkey group by o_custkey) select c_custkey as id, c_acctbal, orders, round(spend, 4) as spend, round(items, 4) as items, round(disc, 9) as disc from customer join c on o_custkey = c_custkey")
def customer_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = workloads.profile_customers(spark, sf_dir)
    return p.select("id", "c_acctbal", "orders", F.round("spend", 4).alias("spend"), F.round("items", 4).alias("items"), F.round("disc", 9).alias("disc"))


@register()
def profile_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers in five groups, with each group's size and mean features."""
    f = workloads.profile_customers(spark, sf_dir)
    p = workloads.standardised(f, "id", ["c_acctbal", "orders", "spend", "items", "disc"])
    labels = workloads.fit_labels(p, 5, max_iter=200)
    return f.join(labels, "id").groupBy("cluster").agg(F.count(F.lit(1)).alias("customers"), *[F.round(F.avg(c), 4).alias(c) for c in ("c_acctbal", "orders", "spend", "items", "disc")])


@register()
def group_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = workloads.group_pages(spark, sf_dir)
    return workloads.fit_labels(p, 4, max_iter=200).groupBy("cluster").count()


@register()
def group_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = workloads.group_turns(spark, sf_dir)
    return workloads.fit_labels(p, 3, max_iter=200).groupBy("cluster").count()


@register(f"with {_E}, n as (select id, sqrt(sum(v * v)) as n from e group by id), g as (select a.id as a, b.id as b, sum(a.v * b.v) as s from e a join e b on a.j = b.j and a.label = b.label and a.id < b.id group by a.id, b.id) select a, b, round(s / (x.n * y.n), 6) as cosine from g join n x on x.id = a join n y on y.id = b where s / (x.n * y.n) >= 0.3")
def near_copy_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of one cluster (here: label) above a cosine."""
    e = from_embeddings(spark, sf_dir)
    got = workloads.dedup_groups(e.select("id", "x"), e.select("id", F.col("truth").alias("cluster")), 0.3)
    return got.select("a", "b", F.round("cosine", 6).alias("cosine"))


@register(f"with {_E}, q as (select * from e where id < 5), d as (select q.id as query, m.label as c, round(sum((q.v - m.v) * (q.v - m.v)), 12) as d from q join m using (j) group by 1, 2), pr as (select query, c from (select *, row_number() over (partition by query order by d, c) as rn from d) where rn <= 2), near as (select id, c from (select id, c, row_number() over (partition by id order by round(d, 12), c) as rn from (select e.id, m.label as c, sum((e.v - m.v) * (e.v - m.v)) as d from e join m using (j) group by 1, 2)) where rn = 1), s as (select pr.query, near.id from pr join near using (c)), r as (select s.query, s.id, sum((e.v - q.v) * (e.v - q.v)) as d from s join e on e.id = s.id join q on q.id = s.query and q.j = e.j group by 1, 2) select query, id, round(d, 6) as distance2 from (select *, row_number() over (partition by query order by d, id) as rn from r) where rn <= 5")
def retrieve_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Probe the two nearest centroids, then the five nearest rows in their clusters."""
    import numpy as np

    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    c = np.array([r["mean"] for r in means(p, "truth").orderBy("truth").collect()])  # ten rows
    got = workloads.retrieve(p.select("id", "x"), c, p.where("id < 5").select("id", "x"), 2, 5)
    return got.select("query", "id", F.round("distance2", 6).alias("distance2"))


@register("select event_id as id, coalesce((props->>'k')::DOUBLE, 0) as k from events")
def points_from_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = from_json(read_table(spark, sf_dir, "events", ["event_id", "props"]), "event_id", "props", ["k"])
    return p.select("id", F.col("x")[0].alias("k"))


@register()
def assign_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A distributed Lloyd run of a few sweeps, with its cluster sizes."""
    labels, _, _ = lloyd.fit(from_embeddings(spark, sf_dir), 10, 1, max_iter=5)
    return labels.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
