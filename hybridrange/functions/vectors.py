"""Vector arithmetic as column expressions: double sums from left to right."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, x: s + x)


def products(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x.cast("double") * y.cast("double"))


def l2sq(a: Column | str, b: Column | str) -> Column:
    """Squared Euclidean distance."""
    return total(F.zip_with(_c(a), _c(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def dot(a: Column | str, b: Column | str) -> Column:
    return total(products(a, b))


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    """One less the cosine; null where a vector is zero."""
    return 1 - F.try_divide(dot(a, b), norm(a) * norm(b))


def normalize(a: Column | str) -> Column:
    length = norm(a)
    return F.transform(_c(a), lambda x: F.try_divide(x.cast("double"), length))


def add_scaled(a: Column | str, b: Column | str, by: float) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x.cast("double") + F.lit(by) * y.cast("double"))


def distance(metric: str, a: Column | str, b: Column | str) -> Column:
    """Euclidean (``l2``) or cosine distance."""
    if metric == "l2":
        return F.sqrt(l2sq(a, b))
    if metric == "cosine":
        return cosine(a, b)
    raise ValueError(f"unknown metric {metric}")
