"""Vectors and packed symmetric matrices as Column expressions over arrays."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def outer_packed(a: Column) -> Column:
    """Upper triangle of the outer product, row by row."""
    return F.flatten(F.transform(a, lambda x, i: F.transform(F.filter(a, lambda _, j: j >= i), lambda y: x * y)))


def kron_vec(a: Column, b: Column) -> Column:
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x * y)))


def mat_vec(packed: Column, v: Column) -> Column:
    """Product of a packed symmetric matrix with a vector."""
    n = F.size(v)
    at = lambda i, j: F.get(packed, (F.least(i, j) * (2 * n - F.least(i, j) - 1) / 2).cast("int") + F.greatest(i, j))
    return F.transform(v, lambda _, i: F.aggregate(F.transform(v, lambda y, j: at(i, j) * y), F.lit(0.0), lambda s, x: s + x))
