"""Around the method on streams: scoring with a frozen model, mergeable moments, cluster mixes, drift, refits."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import vectors
from factorclust.operators.solver import state_folder


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there. New rows go to files of the shared folder, with a checkpoint; aggregates, which
    are rewritten as they grow, to a table in memory (they have a row a group)."""
    if mode == "append":
        top = f"{state_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
        df.writeStream.format("parquet").option("path", f"{top}/rows").option("checkpointLocation", f"{top}/checkpoint").trigger(availableNow=True).start().awaitTermination()
        return df.sparkSession.read.schema(df.schema).parquet(f"{top}/rows")
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def assign_column(x: Column, centroids: np.ndarray) -> Column:
    """Nearest centroid, as a built-in expression: stateless, for streams and batches alike."""
    c = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in centroids])
    return (F.array_min(F.transform(c, lambda m, i: F.struct(vectors.sqdist(x, m).alias("d"), i.alias("i"))))["i"]).cast("int")


def stream_assign(stream: DataFrame, centroids: np.ndarray, x: Column) -> DataFrame:
    return stream.withColumn("cluster", assign_column(x, centroids))


def moments(df: DataFrame, value: str, *by: Column | str) -> DataFrame:
    """Count, sum and sum of squares: they merge by addition, over micro-batches as over partitions."""
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias("s"), F.sum(F.col(value) * F.col(value)).alias("q"))


def cluster_mix(df: DataFrame, cluster: Column | str, how: str = "tumbling", length: str = "1 day", slide: str = "12 hours", watermark: str = "1 hour") -> DataFrame:
    """Rows of each cluster in tumbling, sliding or session windows; rows later than the watermark are dropped on streams."""
    w = {"tumbling": lambda: F.window("ts", length), "sliding": lambda: F.window("ts", length, slide), "session": lambda: F.session_window("ts", length)}[how]()
    timed = df.withWatermark("ts", watermark) if df.isStreaming else df
    return timed.groupBy(w.alias("w"), (F.col(cluster) if isinstance(cluster, str) else cluster).alias("cluster")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("begins"), F.col("w.end").alias("ends"), "cluster", "n")


DRIFT_OUT, DRIFT_STATE = "cluster string, rows long, far long, alarm boolean", "rows long, far long"


def drift(df: DataFrame, bound: float, share: float, value: str = "value", cluster: str = "event_type", timeout_ms: int | None = None) -> DataFrame:
    """Keeps rows and far rows of each cluster; tells with each batch whether the share of far rows is too large.

    With ``timeout_ms`` a cluster that falls silent is forgotten; such a query goes on until it is stopped.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows, far = state.get if state.exists else (0, 0)
        for b in batches:
            rows += len(b)
            far += int((b[value] > bound).sum())
        state.update((rows, far))
        if timeout_ms:
            state.setTimeoutDuration(timeout_ms)
        yield pd.DataFrame([(key[0], rows, far, far > share * rows)], columns=["cluster", "rows", "far", "alarm"])

    return df.groupBy(cluster).applyInPandasWithState(update, DRIFT_OUT, DRIFT_STATE, "update", GroupStateTimeout.ProcessingTimeTimeout if timeout_ms else GroupStateTimeout.NoTimeout)


def dedup(df: DataFrame, key: str, watermark: str = "1 day") -> DataFrame:
    return df.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key]) if df.isStreaming else df.dropDuplicates([key])


def with_labels(stream: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    """Stream to static table."""
    return stream.join(labels, key, "left")


def views_then_purchases(df: DataFrame, within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Purchases of a user soon after a view: a join of two streams over an interval."""
    timed = df.withWatermark("ts", watermark) if df.isStreaming else df
    v = timed.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    p = timed.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return v.join(p, F.expr(f"u1 = u2 and t2 > t1 and t2 <= t1 + interval {within}")).select("view_id", "purchase_id")


def periodic_refit(stream: DataFrame, fit: Callable[[DataFrame, int], None], checkpoint: str, every: str | None = "1 hour"):
    """Calls ``fit`` with each micro-batch, or once with what there is if ``every`` is None; the query restarts from its checkpoint."""
    writer = stream.writeStream.foreachBatch(fit).option("checkpointLocation", checkpoint)
    return writer.trigger(processingTime=every) if every else writer.trigger(availableNow=True)
