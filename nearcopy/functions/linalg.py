"""Vector arithmetic as Catalyst expressions; all of it stays in the JVM."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def doubles(x: Column) -> Column:
    return x.cast("array<double>")


def total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(x: Column, y: Column) -> Column:
    return total(F.zip_with(doubles(x), doubles(y), lambda a, b: a * b))


def squared_l2(x: Column, y: Column) -> Column:
    return total(F.zip_with(doubles(x), doubles(y), lambda a, b: (a - b) * (a - b)))


def l2(x: Column, y: Column) -> Column:
    return F.sqrt(squared_l2(x, y))


def norm(x: Column) -> Column:
    return F.sqrt(total(F.transform(doubles(x), lambda a: a * a)))


def cosine(x: Column, y: Column) -> Column:
    size = norm(x) * norm(y)
    return F.when(size > 0, dot(x, y) / size)


def add(x: Column, y: Column) -> Column:
    return F.zip_with(doubles(x), doubles(y), lambda a, b: a + b)


def subtract(x: Column, y: Column) -> Column:
    return F.zip_with(doubles(x), doubles(y), lambda a, b: a - b)


def scale(x: Column, by: Column | float) -> Column:
    return F.transform(doubles(x), lambda a: a * by)


def normalise(x: Column) -> Column:
    """Unit vector; a zero vector stays."""
    n = norm(x)
    return F.when(n > 0, scale(x, 1 / n)).otherwise(doubles(x))


def block(x: Column, number: Column | int, size: int) -> Column:
    """Block `number` (from 0) of `size` values."""
    return F.slice(x, F.lit(number) * size + 1 if isinstance(number, int) else number * size + 1, size)


def split_blocks(x: Column, m: int, size: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.slice(x, i * size + 1, F.lit(size)))


def is_near_copy(self_distance: Column, distance: Column, tolerance: Column | float) -> Column:
    """The relative test in multiplied form; where the self-distance is 0 only an equal distance passes."""
    gap = F.abs(self_distance - distance)
    return F.when(self_distance <= 1e-12, gap <= 1e-12).otherwise(gap < self_distance * tolerance)
