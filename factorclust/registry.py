"""The registered queries and, where SQL can express them, their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(oracle: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    """Registers a function of (spark, sf_dir) under its own name, with the SQL that gives the same rows."""

    def add(f: Query) -> Query:
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"{key} is registered twice")
        QUERIES[key] = f
        if oracle is not None:
            ORACLES[key] = oracle
        return f

    return add


def register_sql(name: str, text: str, views: tuple[str, ...], oracle: str | None = None) -> None:
    """A query written in Spark SQL over the named tables; the same text is its oracle unless another is given."""
    from factorclust.sources.tables import read_table

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        frames = {v: read_table(spark, sf_dir, v) for v in views}
        return spark.sql(text.format(**{v: f"{{{v}}}" for v in views}), **frames)

    register(oracle if oracle is not None else text.format(**{v: v for v in views}), name)(run)
