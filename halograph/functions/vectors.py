"""Arithmetic on array columns, and the dyadic weights whose sums are exact in any order."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


EDGE = 0.31830988618


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def scaled(a: Column, by: Column) -> Column:
    """Every element times a scalar, without repeating the scalar for each element."""
    return F.transform(a, lambda x: x * by)


def relu(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0))


def leaky_relu(x: Column, slope: float = 0.2) -> Column:
    return F.when(x >= 0, x).otherwise(x * F.lit(slope))


def sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


def millionths(x: Column) -> Column:
    """A whole number of millionths, for comparing engines. The offset keeps exact halves, where the last bit would decide, off the edge."""
    return F.floor(x * F.lit(1e6) + F.lit(EDGE)).cast("long")


def dyadic(i, j, salt: int):
    """Weight (i, j): a multiple of 1/16 between -1/2 and 1/2. Works on columns, arrays and numbers."""
    n = 7 * i + 13 * j + salt
    return (F.pmod(n, F.lit(17)) - 8) / F.lit(16.0) if isinstance(n, Column) else (n % 17 - 8) / 16.0


def dyadic_matrix(rows: int, cols: int, salt: int) -> np.ndarray:
    return dyadic(np.arange(rows)[:, None], np.arange(cols)[None, :], salt)


def weight_table(spark: SparkSession, matrix: np.ndarray) -> DataFrame:
    """A small matrix as rows (i, j, w)."""
    rows = [(i, j, float(matrix[i, j])) for i in range(matrix.shape[0]) for j in range(matrix.shape[1])]
    return spark.createDataFrame(rows, "i int, j int, w double")
