"""Vectorised Python functions, for scoring with many centroids where an expression would grow too long."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type


def assign_nearest(centroids: np.ndarray):
    """A pandas function of an array column: the nearest centroid; ties go to the lowest index."""
    from factorclust.operators.kernel import nearest

    def score(x: pd.Series) -> pd.Series:
        return pd.Series(nearest(np.stack(x.to_numpy()), centroids)[0].astype(np.int32) if len(x) else [], dtype="int32")

    score.__annotations__ = {"x": pd.Series, "return": pd.Series}
    return F.pandas_udf(score, "int")


def gram_by(points: DataFrame, group: str, d: int) -> DataFrame:
    """(group, i, j, g), i <= j: the Gram matrix of each group's vectors. A task sends one triangle for each group it has seen."""
    upper = np.triu_indices(d)
    kind = points.schema[group].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[object, np.ndarray] = {}
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d)
            keys = np.array(b.column(0).to_pylist(), object)
            for key in dict.fromkeys(keys.tolist()):
                mine = x[keys == key]
                sums[key] = sums.get(key, 0.0) + (mine.T @ mine)[upper]
        for key, g in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([key], to_arrow_type(kind)), pa.array([g.tolist()], pa.list_(pa.float64()))], names=["group", "g"])

    parts = points.select(F.col(group).alias("group"), "x").mapInArrow(run, f"group {kind.simpleString()}, g array<double>")
    place = lambda a: F.element_at(F.array(*[F.lit(int(v)) for v in a]), F.col("at") + 1)
    each = parts.select("group", F.posexplode("g").alias("at", "v")).groupBy("group", "at").agg(F.sum("v").alias("g"))
    return each.select(F.col("group").alias(group), place(upper[0]).alias("i"), place(upper[1]).alias("j"), "g")
