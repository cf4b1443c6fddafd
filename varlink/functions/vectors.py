"""Vector algebra on ``ARRAY<DOUBLE>`` columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_ZERO = 0.0


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(_ZERO), lambda s, x: s + x)


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column, by: Column | float) -> Column:
    by = by if isinstance(by, Column) else F.lit(float(by))
    return F.transform(a, lambda x: x * by)


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def sq_dist(a: Column, b: Column) -> Column:
    """Squared Euclidean distance."""
    return _sum(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def mean_vector(vec: str, weight: str | None = None, width: int | None = None) -> Column:
    """Aggregate: the (weighted) mean of array column ``vec`` of known ``width``, as partial sums per element."""
    if width is None:
        raise ValueError("the width of the vectors must be known, so that the aggregate stays map-side combinable")
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    return F.array(*[F.sum(F.col(vec)[i].cast("double") * w) / F.sum(w) for i in range(width)])
