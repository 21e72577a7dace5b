"""Agreement of clusters with labels, from the contingency table; scores of runs and their summary."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(assign: DataFrame, truth: DataFrame) -> DataFrame:
    """(cluster, label, n) by a join on id."""
    return assign.join(truth, "id").groupBy("cluster", "label").agg(F.count(F.lit(1)).alias("n"))


def ari(table: DataFrame) -> DataFrame:
    """The adjusted Rand index of a contingency table; 1 where both sides are trivial."""
    pairs = lambda c: c * (c - 1) / 2
    cells = table.agg(F.sum(pairs(F.col("n"))).alias("both"), F.sum("n").alias("total"))
    rows = table.groupBy("cluster").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("rows"))
    cols = table.groupBy("label").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("cols"))
    expected = F.col("rows") * F.col("cols") / pairs(F.col("total"))
    most = (F.col("rows") + F.col("cols")) / 2
    return cells.join(rows).join(cols).select(F.when(most == expected, 1.0).otherwise((F.col("both") - expected) / (most - expected)).alias("ari"))


def nmi(table: DataFrame, norm: str = "arithmetic") -> DataFrame:
    """Normalised mutual information; the normaliser is the entropies' mean, root, min, max, or the joint entropy."""
    e = entropies(table)
    a, b, joint = F.col("h_cluster"), F.col("h_label"), F.col("h_joint")
    under = {"arithmetic": (a + b) / 2, "geometric": F.sqrt(a * b), "min": F.least(a, b), "max": F.greatest(a, b), "joint": joint}[norm]
    return e.select(F.when(under > 1e-15, (a + b - joint) / under).otherwise(1.0).alias("nmi"))


def entropies(table: DataFrame) -> DataFrame:
    total = F.broadcast(table.agg(F.sum("n").alias("total")))

    def h(df: DataFrame, name: str) -> DataFrame:
        p = F.col("n") / F.col("total")
        return df.join(total).agg((-F.sum(p * F.ln(p))).alias(name))

    rows = table.groupBy("cluster").agg(F.sum("n").alias("n"))
    cols = table.groupBy("label").agg(F.sum("n").alias("n"))
    return h(rows, "h_cluster").join(h(cols, "h_label")).join(h(table, "h_joint"))


def purity(table: DataFrame) -> DataFrame:
    return table.groupBy("cluster").agg(F.max("n").alias("most"), F.sum("n").alias("n")).agg((F.sum("most") / F.sum("n")).alias("purity"))


def v_measure(table: DataFrame) -> DataFrame:
    """Homogeneity, completeness and their harmonic mean."""
    e = entropies(table)
    mutual = F.col("h_cluster") + F.col("h_label") - F.col("h_joint")
    hom = F.when(F.col("h_label") > 0, mutual / F.col("h_label")).otherwise(1.0)
    com = F.when(F.col("h_cluster") > 0, mutual / F.col("h_cluster")).otherwise(1.0)
    return e.select(hom.alias("homogeneity"), com.alias("completeness")).withColumn("v", F.when(F.col("homogeneity") + F.col("completeness") > 0, 2 * F.col("homogeneity") * F.col("completeness") / (F.col("homogeneity") + F.col("completeness"))).otherwise(0.0))


def label_profile(df: DataFrame, label: str) -> DataFrame:
    """(classes, largest, smallest, total)."""
    return df.groupBy(label).agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("classes"), F.max("n").alias("largest"), F.min("n").alias("smallest"), F.sum("n").alias("total"))


def matching(cost: np.ndarray) -> list[int]:
    """The column of each row in a one-to-one match of least cost (square matrix; shortest augmenting paths)."""
    n = len(cost)
    u, v, owner = np.zeros(n), np.zeros(n + 1), np.full(n + 1, -1)
    for i in range(n):
        owner[n] = i
        at, low, came, done = n, np.full(n, np.inf), np.full(n, n), np.zeros(n + 1, bool)
        while owner[at] >= 0:
            done[at] = True
            row = owner[at]
            slack = cost[row] - u[row] - v[:n]
            better = ~done[:n] & (slack < low)
            low[better], came[better] = slack[better], at
            open_ = np.where(done[:n], np.inf, low)
            to = int(np.argmin(open_))
            delta = open_[to]
            for j in np.flatnonzero(done):
                u[owner[j]] += delta
                v[j] -= delta
            low[~done[:n]] -= delta
            at = to
        while at != n:
            owner[at], at = owner[came[at]], came[at]
    out = [0] * n
    for j in range(n):
        out[owner[j]] = j
    return out


def table_np(labels: np.ndarray, truth: np.ndarray) -> np.ndarray:
    a = np.unique(labels, return_inverse=True)[1]
    b = np.unique(truth, return_inverse=True)[1]
    out = np.zeros((a.max() + 1, b.max() + 1), np.int64)
    np.add.at(out, (a, b), 1)
    return out


def scores_np(labels: np.ndarray, truth: np.ndarray) -> dict[str, float]:
    """ARI, NMI (arithmetic), misclustering and purity of labels in memory."""
    return scores_of(table_np(np.asarray(labels), np.asarray(truth)))


def scores_of(table: np.ndarray) -> dict[str, float]:
    """The same of a contingency table."""
    t = np.asarray(table, float)
    n = t.sum()
    c2 = lambda x: (x * (x - 1) / 2).sum()
    both, rows, cols = c2(t), c2(t.sum(1)), c2(t.sum(0))
    expected, most = rows * cols / max(1.0, n * (n - 1) / 2), (rows + cols) / 2
    h = lambda x: -sum(p * math.log(p) for p in (x[x > 0] / n).tolist())
    ha, hb, hj = h(t.sum(1)), h(t.sum(0)), h(t.ravel())
    return {"ari": 1.0 if most == expected else float((both - expected) / (most - expected)), "nmi": (ha + hb - hj) / ((ha + hb) / 2) if ha + hb > 1e-15 else 1.0, "error": misclustering_np(t), "purity": float(t.max(1).sum() / n)}


def misclustering_np(t: np.ndarray) -> float:
    """One less the share of the best one-to-one match of clusters and labels."""
    size = max(t.shape)
    square = np.zeros((size, size))
    square[: t.shape[0], : t.shape[1]] = t
    return float(1 - sum(square[i, j] for i, j in enumerate(matching(-square))) / t.sum())


def misclustering(table: DataFrame, most: int = 2_000) -> float:
    """The same from a contingency DataFrame, of at most ``most`` clusters and labels."""
    return misclustering_np(collected(table, most))


def collected(table: DataFrame, most: int = 2_000) -> np.ndarray:
    """A contingency DataFrame as a matrix, of at most ``most`` clusters and labels."""
    rows = table.collect() if table.count() <= most * most else None
    if rows is None:
        raise ValueError(f"more than {most} clusters or labels")
    a = {c: i for i, c in enumerate(sorted({r.cluster for r in rows}))}
    b = {c: i for i, c in enumerate(sorted({r.label for r in rows}))}
    t = np.zeros((len(a), len(b)))
    for r in rows:
        t[a[r.cluster], b[r.label]] = r.n
    return t


SCORED = "run_id long, method string, seed int, rank int, cap int, iters int, feas double, move double, objective double, wcss double, seconds double, status string, ari double, nmi double, error double"


def score_runs(runs: DataFrame, truth: np.ndarray) -> DataFrame:
    """Scores of grouped runs (labels in the order of ids), one row a run."""
    held = runs.sparkSession.sparkContext.broadcast(np.unique(np.asarray(truth).astype(str), return_inverse=True)[1])

    def run(batches):
        for b in batches:
            s = [scores_np(np.asarray(x), held.value) for x in b.labels]
            yield b.drop(columns=["labels", "bound_ok"]).assign(ari=[v["ari"] for v in s], nmi=[v["nmi"] for v in s], error=[v["error"] for v in s])

    return runs.mapInPandas(run, SCORED)


def summarise(results: DataFrame, by: list[str], value: str) -> DataFrame:
    """Quartiles, mean and range over runs."""
    q = lambda p: F.percentile(value, F.lit(p))
    return results.groupBy(*by).agg(q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.avg(value).alias("mean"), F.min(value).alias("low"), F.max(value).alias("high"), F.count(F.lit(1)).alias("runs"))


def success_rate(results: DataFrame, by: list[str], floor: float, slack: float = 1e-9) -> DataFrame:
    return results.groupBy(*by).agg(F.avg((F.col("error") <= floor + slack).cast("double")).alias("success"), F.count(F.lit(1)).alias("runs"))
