"""Distances and query vectors as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _sum(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda a, x: a + x)


def l2sq(a: Column, b: Column) -> Column:
    """Squared Euclidean distance of two arrays."""
    return _sum(F.zip_with(a, b, lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)))


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x.cast("double") * y))


def norm(a: Column) -> Column:
    return F.sqrt(_sum(F.transform(a, lambda x: x.cast("double") * x.cast("double"))))


def cosine_distance(a: Column, b: Column) -> Column:
    return 1 - dot(a, b) / (norm(a) * norm(b))


def distance(a: Column, b: Column, metric: str = "l2sq") -> Column:
    """Smaller is nearer, for any metric."""
    return {"l2sq": l2sq, "cosine": cosine_distance, "ip": lambda x, y: -dot(x, y)}[metric](a, b)


def query_vector(qid: Column, dim: int) -> Column:
    """Closed-form pseudo-random vector of a query: the same in any engine, no generator state."""
    q = qid.cast("long")
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda d: ((q * 7919 + d * 104729 + q * d * 17) % 2003) / F.lit(1001.5) - 1)
