"""Kernels, distances and vector arithmetic as columns, inside the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def as_doubles(x: Column) -> Column:
    """array<float> is cast before it is multiplied, so that sums do not depend on the engine's float width."""
    return x.cast("array<double>")


def total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda s, v: s + v)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(as_doubles(a), as_doubles(b), lambda u, v: u * v))


def squared_l2(a: Column, b: Column) -> Column:
    return total(F.zip_with(as_doubles(a), as_doubles(b), lambda u, v: (u - v) * (u - v)))


def l1(a: Column, b: Column) -> Column:
    return total(F.zip_with(as_doubles(a), as_doubles(b), lambda u, v: F.abs(u - v)))


def scaled(x: Column, by: Column | float) -> Column:
    factor = by if isinstance(by, Column) else F.lit(float(by))
    return F.transform(as_doubles(x), lambda v: v * factor)


def added(a: Column, b: Column) -> Column:
    return F.zip_with(as_doubles(a), as_doubles(b), lambda u, v: u + v)


def unit(x: Column) -> Column:
    """x over its length; a zero vector stays. The length is bound once, as a lambda would evaluate it for each entry."""
    size = F.sqrt(dot(x, x))
    bound = F.array(F.struct(as_doubles(x).alias("v"), F.when(size > 0, 1.0 / size).otherwise(F.lit(1.0)).alias("by")))
    return F.get(F.transform(bound, lambda s: F.transform(s["v"], lambda v: v * s["by"])), 0)


def rbf(a: Column, b: Column, sigma: float) -> Column:
    return F.exp(-squared_l2(a, b) / (2.0 * sigma * sigma))


def laplacian(a: Column, b: Column, sigma: float) -> Column:
    return F.exp(-l1(a, b) / sigma)


def linear(a: Column, b: Column) -> Column:
    return dot(a, b)


def polynomial(a: Column, b: Column, degree: int = 5, coef0: float = 1.0) -> Column:
    return F.pow(dot(a, b) + coef0, F.lit(float(degree)))


def neural(a: Column, b: Column, slope: float = 0.0045, offset: float = 0.11) -> Column:
    return F.tanh(slope * dot(a, b) + offset)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def jaccard(a: Column, b: Column) -> Column:
    """Of arrays taken as sets; 0 for two empty ones."""
    every = F.size(F.array_union(a, b))
    return F.when(every > 0, F.size(F.array_intersect(a, b)) / every).otherwise(F.lit(0.0))


def histogram_intersection(a: Column, b: Column) -> Column:
    """Of map<string, double>."""
    both = F.map_zip_with(a, b, lambda _, u, v: F.least(F.coalesce(u, F.lit(0.0)), F.coalesce(v, F.lit(0.0))))
    return total(F.map_values(both))


def rounded(x: Column, digits: int = 6) -> Column:
    """Rounded for comparison across engines; adding 0 turns -0 into 0."""
    return F.round(x, digits) + F.lit(0.0)
