"""Streaming queries run to their end, beside the SQL of their batch twins; table functions and the data source."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.plans.pieces import r6
from factorclust.registry import register
from factorclust.sources.points import from_embeddings
from factorclust.sources.tables import read_table
from factorclust.streaming import streams


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


#: Three centres on the line of an event's value.
CENTRES = np.array([[10.0], [50.0], [90.0]])


@register("select event_id, (case when abs(value - 10) <= abs(value - 50) and abs(value - 10) <= abs(value - 90) then 0 when abs(value - 50) <= abs(value - 90) then 1 else 2 end)::INTEGER as cluster from events")
def stream_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = streams.stream_assign(streams.event_stream(spark, sf_dir), CENTRES, F.array("value")).select("event_id", "cluster")
    return streams.run_to_end(s, "stream_assign_out")


@register("select event_type, count(*) as n, round(sum(value), 4) as s, round(sum(value * value), 4) as q from events group by event_type")
def stream_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = streams.moments(streams.event_stream(spark, sf_dir), "value", "event_type")
    return streams.run_to_end(s, "stream_moments_out", "complete").select("event_type", "n", F.round("s", 4).alias("s"), F.round("q", 4).alias("q"))



@register("select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type as cluster, count(*) as n from events group by 1, 2")
def cluster_mix_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Complete mode, so that the last windows are told too."""
    s = streams.cluster_mix(streams.event_stream(spark, sf_dir), "event_type", "tumbling")
    return streams.run_to_end(s, "cluster_mix_out", "complete").select(F.date_format("begins", "yyyy-MM-dd").alias("day"), "cluster", "n")


@register("select strftime(w, '%Y-%m-%d %H') as begins, event_type as cluster, count(*) as n from (select event_type, unnest([time_bucket(interval 12 hour, ts), time_bucket(interval 12 hour, ts) - interval 12 hour]) as w from events) group by 1, 2")
def cluster_mix_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.cluster_mix(events(spark, sf_dir), "event_type", "sliding").select(F.date_format("begins", "yyyy-MM-dd HH").alias("begins"), "cluster", "n")


@register("with g as (select event_type, ts, case when ts - lag(ts) over w < interval 10 minute then 0 else 1 end as fresh from events window w as (partition by event_type order by ts)), s as (select event_type, sum(fresh) over (partition by event_type order by ts rows unbounded preceding) as k from g) select event_type as cluster, count(*) as n, count(distinct k) as sessions from s group by event_type")
def cluster_mix_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = streams.cluster_mix(events(spark, sf_dir), "event_type", "session", "10 minutes")
    return s.groupBy("cluster").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("sessions"))


@register("select event_type as cluster, count(*) as rows, count(*) filter (where value > 80) as far, count(*) filter (where value > 80) > 0.2 * count(*) as alarm from events group by event_type")
def drift_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = streams.drift(streams.event_stream(spark, sf_dir), 80.0, 0.2)
    told = streams.run_to_end(s, "drift_out", "update")
    return told.groupBy("cluster").agg(F.max("rows").alias("rows"), F.max_by("far", "rows").alias("far"), F.max_by("alarm", "rows").alias("alarm"))


@register("select count(distinct event_id) as n from events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = streams.event_stream(spark, sf_dir)
    return streams.run_to_end(streams.dedup(s.select("event_id", "ts"), "event_id", "40 days"), "dedup_out").agg(F.count(F.lit(1)).alias("n"))


@register("select e.event_id, c.c_mktsegment from events e left join customer c on c.c_custkey = e.user_id")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    s = streams.with_labels(streams.event_stream(spark, sf_dir).select("event_id", "user_id"), c, "user_id").select("event_id", "c_mktsegment")
    return streams.run_to_end(s, "static_join_out")


@register("select v.event_id as view_id, p.event_id as purchase_id from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts > v.ts and p.ts <= v.ts + interval 1 hour")
def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.run_to_end(streams.views_then_purchases(streams.event_stream(spark, sf_dir)), "stream_join_out")


# --- table functions and the data source ------------------------------------------------------------------------


@register()
def udtf_cluster(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factorclust.functions.udtf import register_table_functions

    register_table_functions(spark)
    from_embeddings(spark, sf_dir).select("id", "x").createOrReplaceTempView("factorclust_points")
    return spark.sql("select cluster, status, count(*) as n from nfk_cluster(table(factorclust_points) with single partition, 4, 8) group by cluster, status")


@register("with g as (select c_mktsegment, count(c_acctbal) as n from customer group by 1), t as (select truth, sum(n // 5 + (case when truth < n % 5 then 1 else 0 end)) as n from g, (select unnest(range(5)) as truth) group by truth) select sum(n)::BIGINT as n, count(*)::BIGINT as classes, min(n)::BIGINT as smallest from t")
def udtf_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A mixture for each market segment, of as many points as it has customers."""
    from factorclust.functions.udtf import register_table_functions

    register_table_functions(spark)
    sizes = read_table(spark, sf_dir, "customer", ["c_mktsegment", "c_acctbal"]).groupBy("c_mktsegment").agg(F.count("c_acctbal").alias("size"))
    rows = spark.sql("select truth, count(*) as n from {sizes}, lateral planted_mixture(size, 6, 5, 1.0D, 3) group by truth", sizes=sizes)
    return rows.agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("classes"), F.min("n").alias("smallest"))


@register("select count(*) as n, count(distinct o_orderkey % 4) as classes, true as same from orders")
def datasource_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For the keys of orders, the data source gives the rows that the source on spark.range gives."""
    from factorclust.sources.datasource import PlantedMixtureSource
    from factorclust.sources.points import mixture

    spark.dataSource.register(PlantedMixtureSource)
    orders = read_table(spark, sf_dir, "orders", ["o_orderkey"]).select(F.col("o_orderkey").cast("long").alias("id"))
    n = max(2, orders.agg(F.max("id")).first()[0] + 1)
    parts = max(4, spark.sparkContext.defaultParallelism)
    a = spark.read.format("planted_mixture").options(n=str(n), d="6", k="4", gamma="2.0", seed="3", partitions=str(parts)).load().join(orders, "id")
    b = mixture(spark, n, 6, 4, 2.0, 3).join(orders, "id")
    s = lambda df: df.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("truth").alias("classes"), r6(F.sum(F.col("x")[0] * F.col("id"))).alias("s"))
    x, y = s(a), s(b).select(F.col("s").alias("t"))
    return x.join(y).select("n", "classes", (F.abs(F.col("s") - F.col("t")) <= 1e-12 * F.greatest(F.abs("s"), F.lit(1.0)) * F.col("n")).alias("same"))


@register("select event_type, count(*) as n, round(avg(value), 6) as mean from events group by event_type")
def stream_refit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A model (the mean value of each type) made anew with each micro-batch and kept in the shared folder; the last one is returned."""
    from factorclust.operators.solver import state_folder

    top = f"{state_folder(spark)}/refit-{uuid.uuid4().hex}"

    def fit(batch: DataFrame, number: int) -> None:
        sums = batch.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("s"))
        if number:
            sums = sums.unionByName(spark.read.parquet(f"{top}/model-{number - 1}")).groupBy("event_type").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))
        sums.write.mode("overwrite").parquet(f"{top}/model-{number}")  # a batch that is run again writes the same

    query = streams.periodic_refit(streams.event_stream(spark, sf_dir), fit, f"{top}/checkpoint", every=None).start()
    query.awaitTermination()
    last = max(p.batchId for p in query.recentProgress if p.numInputRows)
    return spark.read.parquet(f"{top}/model-{last}").select("event_type", "n", F.round(F.col("s") / F.col("n"), 6).alias("mean"))
