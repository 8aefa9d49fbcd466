"""Vector algebra over ARRAY<DOUBLE> columns and over literal centers; stays inside code generation."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def sqdist(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def matvec(a: Column, matrix: Sequence[Sequence[float]]) -> Column:
    """Row vector times a literal matrix (rows x columns)."""
    columns = len(matrix[0]) if len(matrix) else 0
    return F.array(*(sum((a[i] * F.lit(float(matrix[i][j])) for i in range(len(matrix))), F.lit(0.0)) for j in range(columns)))


def sqdist_to(values: Sequence[Column], center: Sequence[float]) -> Column:
    """Squared distance of unpacked coordinates to a literal center."""
    total = F.lit(0.0)
    for v, c in zip(values, center):
        d = v - F.lit(float(c))
        total = total + d * d
    return total


def nearest(values: Sequence[Column], centers: Sequence[Sequence[float]]) -> tuple[Column, Column]:
    """Number (from 0) of the nearest literal center, ties to the lowest, and the squared distance; nulls if there is no center."""
    if not len(centers):
        return F.lit(None).cast("int"), F.lit(None).cast("double")
    distances = F.array(*(sqdist_to(values, c) for c in centers))
    least = F.array_min(distances)
    return (F.array_position(distances, least) - 1).cast("int"), least
