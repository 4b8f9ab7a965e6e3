"""Column expressions over descriptor vectors: distances, norms, the bisector test, other similarities."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda total, x: total + x)


def sqdist(x: Column, y: Column) -> Column:
    """Squared Euclidean distortion."""
    return _sum(F.zip_with(x, y, lambda a, b: (a - b) * (a - b)))


def dot(x: Column, y: Column) -> Column:
    return _sum(F.zip_with(x, y, lambda a, b: a * b))


def sqnorm(x: Column) -> Column:
    return _sum(F.transform(x, lambda a: a * a))


def sqdist_cached(x: Column, x_norm: Column, y: Column, y_norm: Column) -> Column:
    """The same distortion from squared norms that are kept between iterations."""
    return x_norm - 2 * dot(x, y) + y_norm


def side(x: Column, w: Column, b: Column) -> Column:
    """1 on the far side of the bisector w.x = b of two codewords; the bisector itself belongs to side 0."""
    return (dot(x, w) > b).cast("int")


def cosine_distance(x: Column, y: Column) -> Column:
    norms = F.sqrt(sqnorm(x) * sqnorm(y))
    return F.when(norms > 0, 1 - dot(x, y) / norms).otherwise(F.lit(1.0))


def intersection_distance(x: Column, y: Column) -> Column:
    """1 - histogram intersection, relative to the smaller total."""
    least = F.least(_sum(F.transform(x, lambda a: a.cast("double"))), _sum(F.transform(y, lambda a: a.cast("double"))))
    return F.when(least > 0, 1 - _sum(F.zip_with(x, y, lambda a, b: F.least(a, b).cast("double"))) / least).otherwise(F.lit(1.0))


def chi2_distance(x: Column, y: Column) -> Column:
    return _sum(F.zip_with(x, y, lambda a, b: F.when(a + b > 0, (a - b) * (a - b) / (a + b)).otherwise(F.lit(0.0)))) / 2


METRICS = {"sqeuclid": sqdist, "cosine": cosine_distance, "hist_intersection": intersection_distance, "chi2": chi2_distance}
