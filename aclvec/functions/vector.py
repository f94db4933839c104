"""Distances and other functions of array<float> vectors, as higher-order expressions that stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0).cast("double"), lambda acc, x: acc + x)


def dot(a, b) -> Column:
    return _total(F.zip_with(_col(a), _col(b), lambda x, y: x.cast("double") * y.cast("double")))


def l2sq(a, b) -> Column:
    """Squared Euclidean distance."""
    return _total(F.zip_with(_col(a), _col(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def l2(a, b) -> Column:
    return F.sqrt(l2sq(a, b))


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a, b) -> Column:
    """Cosine similarity; null where a norm is 0."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n)


def normalised(a) -> Column:
    n = norm(a)
    return F.when(n > 0, F.transform(_col(a), lambda x: (x / n).cast("float"))).otherwise(_col(a))


METRICS = {"l2sq": l2sq, "l2": l2, "dot": lambda a, b: -dot(a, b), "cosine": lambda a, b: 1 - cosine(a, b)}
