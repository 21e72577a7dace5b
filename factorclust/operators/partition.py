"""Quantities of a partition: sums of squares two ways, the assignment factor, the membership matrix."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.functions.vectors import norm2, sqdist


def means(points: DataFrame, by: str = "cluster") -> DataFrame:
    """(by, size, mean): sums per entry combine before the shuffle, K x d rows after it."""
    entries = points.select(by, F.posexplode("x").alias("j", "v")).groupBy(by, "j").agg(F.avg("v").alias("m"), F.count(F.lit(1)).alias("size"))
    return entries.groupBy(by).agg(F.max("size").alias("size"), F.transform(F.array_sort(F.collect_list(F.struct("j", "m"))), lambda e: e["m"]).alias("mean"))  # d entries a group


def wcss(points: DataFrame, by: str = "cluster") -> DataFrame:
    """(by, size, wcss): squared distances to the group's mean."""
    centre = F.broadcast(means(points, by))  # K rows
    return points.join(centre, by).groupBy(by).agg(F.count(F.lit(1)).alias("size"), F.sum(sqdist(F.col("x"), F.col("mean"))).alias("wcss"))


def wcss_by_energy(points: DataFrame, by: str = "cluster") -> DataFrame:
    """(total, energy, explained, wcss): total energy less the part that the groups' sums explain; one pass."""
    entries = points.select(by, F.posexplode("x").alias("j", "v")).groupBy(by, "j").agg(F.sum("v").alias("s"), F.sum(F.col("v") * F.col("v")).alias("q"), F.count(F.lit(1)).alias("n"))
    return entries.agg(F.sum("q").alias("energy"), F.sum(F.col("s") * F.col("s") / F.col("n")).alias("explained")).select("energy", "explained", (F.col("energy") - F.col("explained")).alias("wcss"))


def assignment_factor(assign: DataFrame) -> DataFrame:
    """(id, cluster, weight): one over the root of the cluster's size."""
    sizes = assign.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
    return assign.join(F.broadcast(sizes), "cluster").select("id", "cluster", (1 / F.sqrt("size")).alias("weight"))


def membership_matrix(assign: DataFrame, most: int = 4000) -> DataFrame:
    """(i, j, v) of the n x n membership matrix, for small n: the product of the factor with its transpose."""
    if assign.limit(most + 1).count() > most:
        raise ValueError(f"the membership matrix is formed for at most {most} points")
    f = assignment_factor(assign)
    a = f.select(F.col("id").alias("i"), "cluster", F.col("weight").alias("a"))
    b = f.select(F.col("id").alias("j"), "cluster", F.col("weight").alias("b"))
    return a.join(b, "cluster").select("i", "j", (F.col("a") * F.col("b")).alias("v"))


def membership_rows(factor: DataFrame) -> DataFrame:
    """(i, row_sum) of the membership matrix of any size, from its factor: entries of i are its weight times those of its cluster."""
    sums = factor.groupBy("cluster").agg(F.sum("weight").alias("total"))
    return factor.join(F.broadcast(sums), "cluster").select(F.col("id").alias("i"), (F.col("weight") * F.col("total")).alias("row_sum"))


def membership_product(factor: DataFrame, points: DataFrame) -> DataFrame:
    """(inner_product) of the points' inner products with the membership matrix: the energy of each cluster's weighted sum."""
    entries = factor.join(points.select("id", "x"), "id").select("cluster", "weight", F.posexplode("x").alias("d", "v"))
    sums = entries.groupBy("cluster", "d").agg(F.sum(F.col("weight") * F.col("v")).alias("s"))
    return sums.agg(F.sum(F.col("s") * F.col("s")).alias("inner_product"))


def check_membership(factor: DataFrame, k: int) -> DataFrame:
    """(property, ok, value) of the four properties of the matrix with this factor; it is a projection, so its square has the same trace."""
    w = F.col("weight")
    blocks = factor.groupBy("cluster").agg(F.min(w).alias("least"), F.max(w).alias("most"), F.sum(w * w).alias("own"))
    low = F.when(F.col("least") >= 0, F.col("least") * F.col("least")).when(F.col("most") <= 0, F.col("most") * F.col("most")).otherwise(F.col("least") * F.col("most"))
    t = blocks.agg(F.min(low).alias("low"), F.sum("own").alias("trace"), F.sum(F.col("own") * F.col("own")).alias("square"))
    r = membership_rows(factor).agg(F.max(F.abs(F.col("row_sum") - 1)).alias("off"))
    each = t.join(r).select(F.explode(F.array(
        F.struct(F.lit("nonnegative").alias("property"), (F.col("low") >= 0).alias("ok"), F.col("low").alias("value")),
        F.struct(F.lit("trace").alias("property"), (F.abs(F.col("trace") - k) < 1e-9).alias("ok"), F.col("trace").alias("value")),
        F.struct(F.lit("row_sums").alias("property"), (F.col("off") < 1e-9).alias("ok"), F.col("off").alias("value")),
        F.struct(F.lit("projection").alias("property"), (F.abs(F.col("square") - F.col("trace")) < 1e-9).alias("ok"), F.col("square").alias("value")),
    )).alias("e"))
    return each.select("e.*")


def total_energy(points: DataFrame) -> DataFrame:
    return points.agg(F.sum(norm2(F.col("x"))).alias("energy"))


def separation(points: DataFrame, by: str = "truth") -> DataFrame:
    """(delta, sigma): least distance of two group means, and the noise's standard deviation per entry."""
    m = means(points, by).select(F.col(by).alias("k"), "mean")
    pairs = m.alias("a").join(m.alias("b"), F.col("a.k") < F.col("b.k")).select(F.sqrt(sqdist(F.col("a.mean"), F.col("b.mean"))).alias("far"))
    w = wcss(points, by).agg(F.sum("wcss").alias("w"), F.sum("size").alias("n"), F.count(F.lit(1)).alias("k"))
    d = points.agg(F.max(F.size("x")).alias("d"))
    return pairs.agg(F.min("far").alias("delta")).join(w).join(d).select("delta", F.sqrt(F.col("w") / ((F.col("n") - F.col("k")) * F.col("d"))).alias("sigma"))
