"""Vectors as arrays, inside code generation: unrolled sums, sums of arrays, dot products."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def width(df: DataFrame, column: str = "x") -> int:
    """Length of the vectors, from one row."""
    first = df.select(F.size(column).alias("n")).first()
    return first["n"] if first else 0


def summed(df: DataFrame, key: str, d: int, column: str = "x") -> DataFrame:
    """Vector sum for each key as d plain sums in one hash aggregation, combined before the shuffle."""
    sums = df.groupBy(key).agg(*[F.sum(F.get(column, F.lit(i))).alias(f"_{i}") for i in range(d)])
    return sums.select(key, F.array(*[f"_{i}" for i in range(d)]).alias(column))


def averaged(df: DataFrame, key: str, d: int, column: str = "x") -> DataFrame:
    means = df.groupBy(key).agg(*[F.avg(F.get(column, F.lit(i))).alias(f"_{i}") for i in range(d)])
    return means.select(key, F.array(*[f"_{i}" for i in range(d)]).alias(column))


def plus(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x * y).cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


def softmax(a: Column | str) -> Column:
    e = F.transform(a, lambda x: F.exp(x - F.array_max(a)))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda s, y: s + y))


def argmax(a: Column | str) -> Column:
    return F.array_position(a, F.array_max(a)) - 1


def one_hot(y: Column | str, n: int) -> Column:
    y = F.col(y) if isinstance(y, str) else y
    return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: (i == y).cast("int"))
