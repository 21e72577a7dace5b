"""Tables, files of other formats, and the check that parts fit rows from others."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """A Parquet table; columns and filter are stated so that the scan reads no more."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options: str) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet; a schema is required where the format has none."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", partition: Sequence[str] = (), **options: str) -> None:
    writer = df.write.format(kind).mode(mode).options(**options)
    (writer.partitionBy(*partition) if partition else writer).save(path)


def write_assignment(df: DataFrame, path: str) -> None:
    """Labels in a folder for each cluster, so that reading one cluster reads one folder."""
    write_any(df, path, mode="overwrite", partition=["cluster"])


def append_results(df: DataFrame, path: str) -> None:
    write_any(df, path, mode="append")


def read_results(spark: SparkSession, path: str, key: Sequence[str]) -> DataFrame:
    """Results appended by any number of tries, each run once."""
    return spark.read.parquet(path).dropDuplicates(list(key))


def split_valid(points: DataFrame, width: int, vec: str = "x") -> tuple[DataFrame, DataFrame]:
    """(points that can be clustered, the others with a reason)."""
    v = F.col(vec)
    reason = (
        F.when(v.isNull(), "null")
        .when(F.size(v) != width, "width")
        .when(F.exists(v, lambda x: x.isNull()), "null entry")
        .when(F.exists(v, lambda x: F.isnan(x)), "nan")
        .when(F.exists(v, lambda x: F.abs(x) == F.lit(float("inf"))), "infinite")
    )
    told = points.withColumn("reason", reason)
    return told.where("reason is null").drop("reason"), told.where("reason is not null")
