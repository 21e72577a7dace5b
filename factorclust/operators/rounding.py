"""From a nonnegative factor to labels.

Where the factor is feasible its rows within a cluster agree, and its columns fall into K groups with
disjoint supports. So the columns are grouped, on the small Gram matrix, and a row goes to the group that
holds most of its energy. Row argmax and K-means on the rows are there for comparison.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def column_groups(gram: np.ndarray, k: int) -> list[list[int]]:
    """Merges the two groups of columns with the largest cosine until K are left; faint columns join last."""
    energy = np.diag(gram)
    strong = [j for j in range(len(gram)) if energy[j] > 1e-9 * energy.max()]
    groups = [[j] for j in strong]
    sums = gram[np.ix_(strong, strong)].copy()
    while len(groups) > k:
        scale = np.sqrt(np.maximum(np.diag(sums), 1e-300))
        cos = sums / np.outer(scale, scale)
        np.fill_diagonal(cos, -1)
        a, b = divmod(int(np.argmax(cos)), len(groups))
        a, b = min(a, b), max(a, b)
        sums[a] += sums[b]
        sums[:, a] += sums[:, b]
        sums = np.delete(np.delete(sums, b, 0), b, 1)
        groups[a] = sorted(groups[a] + groups.pop(b))
    while len(groups) < k:
        groups.append([])
    return groups


def labels_of(f: np.ndarray, groups: list[list[int]]) -> np.ndarray:
    energy = np.stack([(f[:, g] ** 2).sum(1) if g else np.zeros(len(f)) for g in groups], axis=1)
    return np.argmax(energy, axis=1)


def round_columns(f: np.ndarray, k: int, gram: np.ndarray | None = None) -> np.ndarray:
    return labels_of(f, column_groups(f.T @ f if gram is None else gram, k))


def round_argmax(f: np.ndarray) -> np.ndarray:
    return np.argmax(f, axis=1)


def round_rows(f: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    from factorclust.operators.lloyd import fit_local

    return fit_local(f, k, seed, seeding="dsq").labels


def label_column(factor: Column, groups: list[list[int]]) -> Column:
    """The same on a column of factor rows: built-in expressions, narrow."""
    total = [sum((F.pow(F.get(factor, F.lit(j)), 2) for j in g), F.lit(0.0)) for g in groups]
    energy = F.array(*total)
    return (F.array_position(energy, F.array_max(energy)) - 1).cast("int")


def canonical(assign: DataFrame) -> DataFrame:
    """Clusters numbered from 0 by their least id."""
    first = assign.groupBy("cluster").agg(F.min("id").alias("first"))
    smaller = first.alias("a").join(F.broadcast(first).alias("b"), F.col("b.first") < F.col("a.first"), "left").groupBy(F.col("a.cluster").alias("cluster")).agg(F.count("b.first").cast("int").alias("rank"))
    return assign.join(F.broadcast(smaller), "cluster").select("id", F.col("rank").alias("cluster"))


def canonical_np(labels: np.ndarray) -> np.ndarray:
    _, first, inverse = np.unique(labels, return_index=True, return_inverse=True)
    rank = np.empty(len(first), np.int64)
    rank[np.argsort(first)] = np.arange(len(first))
    return rank[inverse]
