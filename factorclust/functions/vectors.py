"""Vector functions on ARRAY<DOUBLE> columns, all built-in expressions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def zeros(n: int) -> Column:
    return F.array_repeat(F.lit(0.0), n)


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def norm2(a: Column) -> Column:
    """The squared length."""
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))


def sqdist(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(norm2(a) * norm2(b))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def axpy(s: Column, a: Column, b: Column) -> Column:
    """s * a + b."""
    return F.zip_with(a, b, lambda x, y: s * x + y)


def mul(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def clamp(a: Column) -> Column:
    return F.transform(a, lambda x: F.greatest(x, F.lit(0.0)))


def scale(s: Column, a: Column) -> Column:
    return F.transform(a, lambda x: s * x)


def unit(a: Column) -> Column:
    """The vector at length 1; a zero vector stays."""
    n = F.sqrt(norm2(a))
    return F.transform(a, lambda x: F.when(n > 0, x.cast("double") / n).otherwise(x.cast("double")))


def argmax(a: Column) -> Column:
    """Place of the largest entry from 0; ties: the first."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("int")


def argmin(a: Column) -> Column:
    return (F.array_position(a, F.array_min(a)) - 1).cast("int")


def matvec(m: Column, a: Column) -> Column:
    return F.transform(m, lambda row: dot(row, a))


def reshape(a: Column, width: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.floor((F.size(a) - 1) / width).cast("int")), lambda i: F.slice(a, i * width + 1, width))


def one_hot(k: Column, n: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(i == k, F.lit(1.0)).otherwise(F.lit(0.0)))


#: SQL functions over ARRAY<DOUBLE> that the session may define: name, arguments, result, body.
SQL_FUNCTIONS = (
    ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    ("vec_norm2", "a ARRAY<DOUBLE>", "DOUBLE", "aggregate(a, 0D, (s, x) -> s + x * x)"),
    ("vec_sqdist", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"),
    ("vec_axpy", "s DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> s * x + y)"),
    ("vec_clamp", "a ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "transform(a, x -> greatest(x, 0D))"),
    ("vec_argmin", "a ARRAY<DOUBLE>", "INT", "cast(array_position(a, array_min(a)) - 1 as int)"),
)


def define_sql_functions(spark: SparkSession) -> None:
    for name, arguments, result, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {result} RETURN {body}")
