"""Vector arithmetic on array columns, and activations, as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0.0), lambda total, x: total + x)


def scale(a: Column | str, factor: Column) -> Column:
    return F.transform(_col(a), lambda x: x * factor)


def axpy(factor: Column, x: Column | str, y: Column | str) -> Column:
    """factor * x + y."""
    return F.zip_with(_col(x), _col(y), lambda p, q: factor * p + q)


def vec_add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def vec_sub(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x - y)


def norm2(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def mat_row(a: Column | str, matrix: list[list[float]]) -> Column:
    """Row vector times a small dense matrix (rows of equal length)."""
    a = _col(a)
    return F.array(*[dot(a, F.array(*[F.lit(float(row[k])) for row in matrix])) for k in range(len(matrix[0]))])


def leaky_relu(x: Column, slope: float = 0.2) -> Column:
    return F.when(x >= 0, x).otherwise(x * slope)


def relu(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0))


def elu(x: Column) -> Column:
    return F.when(x >= 0, x).otherwise(F.exp(x) - 1)


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def tanh(x: Column) -> Column:
    return F.tanh(x)


ACTIVATIONS = {"none": lambda x: x, "leaky_relu": leaky_relu, "relu": relu, "elu": elu, "sigmoid": sigmoid, "tanh": tanh}
