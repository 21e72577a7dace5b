"""Points (id LONG, x ARRAY<DOUBLE>) from the tables, planted mixtures, and text features."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import portable, vectors
from factorclust.functions.theory import cnr_threshold
from factorclust.sources.tables import read_table

WIDTH, CLASSES = 64, 10


def from_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, x, truth of the raw embeddings."""
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"])
    return e.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"), F.col("label").alias("truth"))


def from_columns(df: DataFrame, key: str, columns: Sequence[str]) -> DataFrame:
    return df.select(F.col(key).cast("long").alias("id"), F.array(*[F.col(c).cast("double") for c in columns]).alias("x"))


def from_json(df: DataFrame, key: str, column: str, keys: Sequence[str]) -> DataFrame:
    """Numbers of a JSON object in the order of ``keys``; missing ones are 0."""
    parsed = F.from_json(F.col(column), ", ".join(f"`{k}` double" for k in keys))
    return df.select(F.col(key).cast("long").alias("id"), F.array(*[F.coalesce(parsed[k], F.lit(0.0)) for k in keys]).alias("x"))


def planted(spark: SparkSession, sf_dir: str, gamma: float, thin: bool = False) -> DataFrame:
    """The embeddings as noise round centres that lie gamma times the recovery threshold apart.

    ``thin`` leaves unequal classes: ids kept where (id div 10) mod (1 + label) is 0.
    """
    e = from_embeddings(spark, sf_dir)
    n = e.count()
    far = gamma * cnr_threshold(n, WIDTH, CLASSES) / math.sqrt(2)
    noise = vectors.scale(F.lit(math.sqrt(WIDTH)), F.col("x"))
    at = F.transform(noise, lambda v, j: F.when(j == F.col("truth"), v + far).otherwise(v))
    rows = e.select("id", at.alias("x"), "truth")
    return rows.where(F.floor(F.col("id") / 10) % (1 + F.col("truth")) == 0) if thin else rows


def mixture_rows(ids: np.ndarray, n: int, d: int, k: int, gamma: float, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(points, truth) of a balanced mixture with orthogonal centres, for ids of 0..n-1; needs d >= k or d >= 2k is not asked.

    Where d < k the centres are signed unit vectors, then sums of two of them.
    """
    truth = ids % k
    noise = portable.normal_np(ids[:, None], np.arange(d)[None, :], seed)
    return noise + centres(k, d)[truth] * gamma * cnr_threshold(n, d, k) / math.sqrt(2), truth


def centres(k: int, d: int) -> np.ndarray:
    """k points of which any two lie at least sqrt(2) apart."""
    out = np.zeros((k, d))
    for c in range(k):
        sign, lap = (1 if (c // d) % 2 == 0 else -1), c // (2 * d)
        out[c, c % d] = sign
        if lap:
            out[c, (c + lap) % d] = sign * (1 if lap % 2 else -1)
    return out


def mixture(spark: SparkSession, n: int, d: int, k: int, gamma: float, seed: int, partitions: int | None = None) -> DataFrame:
    """A planted mixture of any size from spark.range; nothing is shuffled."""
    base = spark.range(0, n, 1, partitions) if partitions else spark.range(n)

    def rows(batches):
        import pyarrow as pa

        for b in batches:
            ids = b.column(0).to_numpy()
            x, truth = mixture_rows(ids, n, d, k, gamma, seed)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1) * d, pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(ids), lists, pa.array(truth.astype(np.int32))], names=["id", "x", "truth"])

    return base.mapInArrow(rows, "id long, x array<double>, truth int")


def letter_bag(text: Column, width: int) -> Column:
    """Counts of letters by code point modulo ``width``."""
    codes = F.transform(F.split(F.regexp_replace(F.lower(text), r"[^\p{L}]", ""), ""), lambda c: F.pmod(F.ascii(c), F.lit(width)))
    codes = F.filter(codes, lambda c: c.isNotNull())
    return F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda j: F.size(F.filter(codes, lambda c: c == j)).cast("double"))


def pair_bag(text: Column, width: int) -> Column:
    """Counts of neighbouring letters by a hash of the two code points."""
    letters = F.regexp_replace(F.lower(text), r"[^\p{L}]", "")
    code = F.transform(F.split(letters, ""), lambda c: F.ascii(c))
    pairs = F.zip_with(F.slice(code, 1, F.greatest(F.size(code) - 1, F.lit(0))), F.slice(code, 2, F.greatest(F.size(code) - 1, F.lit(0))), lambda a, b: F.pmod(a * 31 + b * 7 + (a * b) % 13, F.lit(width)))
    return F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda j: F.size(F.filter(pairs, lambda c: c == j)).cast("double"))


def document_bands(spark: SparkSession, sf_dir: str, chars: int | None = None) -> DataFrame:
    """id, two bands of letter counts each of unit length, their concatenation x, truth (the language)."""
    d = read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang"])
    rows = letter_counts(d)
    a, b = vectors.unit(F.col("a")), vectors.unit(F.col("b"))
    return rows.select("id", a.alias("band_a"), b.alias("band_b"), F.concat(a, b).alias("x"), "truth")


def letter_counts(documents: DataFrame, letters: int = 32, pairs: int = 64) -> DataFrame:
    """id, a (letter counts), b (letter pair counts), truth; one pass over whole texts in NumPy."""

    def rows(batches):
        import re

        import pyarrow as pa

        other = re.compile(r"[\W\d_]+")
        for batch in batches:
            a, b = [], []
            for text in batch.column(1).to_pylist():
                code = np.frombuffer(other.sub("", (text or "").lower()).encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
                a.append(np.bincount(code % letters, minlength=letters).astype(float))
                x, y = code[:-1], code[1:]
                b.append(np.bincount((x * 31 + y * 7 + (x * y) % 13) % pairs, minlength=pairs).astype(float))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([v.tolist() for v in a], pa.list_(pa.float64())), pa.array([v.tolist() for v in b], pa.list_(pa.float64())), batch.column(2)], names=["id", "a", "b", "truth"])

    return documents.select(F.col("doc_id").alias("id"), "text", F.col("lang").alias("truth")).mapInArrow(rows, "id long, a array<double>, b array<double>, truth string")


def half_bands(points: DataFrame) -> DataFrame:
    """Each half of the vector at unit length."""
    x = F.col("x")
    half = F.floor(F.size(x) / 2).cast("int")
    return points.withColumn("x", F.concat(vectors.unit(F.slice(x, F.lit(1), half)), vectors.unit(F.slice(x, half + 1, F.size(x) - half))))
