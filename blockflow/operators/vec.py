"""Vector expressions over array columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a, b) -> Column:
    """Sum of products; the shorter vector counts as padded with zeros."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + F.coalesce(v, F.lit(0.0)))


def norm(a) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def l2(a) -> Column:
    """Unit length; a zero vector stays zero."""
    return F.transform(a, lambda x: F.coalesce(F.try_divide(x, norm(a)), F.lit(0.0)))


def ratio(product: Column, norm_a: Column, norm_b: Column) -> Column:
    """Cosine from a product and two norms: 0 where either is zero, 1 where both are, never above 1."""
    both = (norm_a == 0) & (norm_b == 0)
    return F.when(both, F.lit(1.0)).otherwise(F.least(F.lit(1.0), F.coalesce(F.try_divide(product, norm_a * norm_b), F.lit(0.0))))


def cosine(a, b) -> Column:
    return ratio(dot(a, b), norm(a), norm(b))


def squared_distance(a, b) -> Column:
    """The shorter vector counts as padded with zeros."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.coalesce(x, F.lit(0.0)) - F.coalesce(y, F.lit(0.0))), F.lit(0.0), lambda s, v: s + v * v)


def gauss(a, b, gamma: float = 5.0) -> Column:
    return F.exp(-gamma * squared_distance(a, b))
