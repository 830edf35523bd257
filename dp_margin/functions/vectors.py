"""Array functions inside the JVM: products, norms, clipping."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(x: Column, z: Column) -> Column:
    return total(F.zip_with(x, z, lambda a, b: a.cast("double") * b.cast("double")))


def dot_literal(x: Column, w) -> Column:
    """x . w for a literal w: a flat sum in generated code while it is short, else one constant array."""
    if len(w) > 16:
        return dot(x, F.array(*[F.lit(float(v)) for v in w]))
    return reduce(lambda a, b: a + b, [F.get(x, F.lit(i)).cast("double") * F.lit(float(v)) for i, v in enumerate(w)])


def norm1(x: Column) -> Column:
    return total(F.transform(x, lambda v: F.abs(v.cast("double"))))


def norm2(x: Column) -> Column:
    return F.sqrt(total(F.transform(x, lambda v: v.cast("double") * v.cast("double"))))


def sup(x: Column) -> Column:
    return F.array_max(F.transform(x, lambda v: F.abs(v.cast("double"))))


def axpy(a: float, x: Column, z: Column) -> Column:
    return F.zip_with(x, z, lambda u, v: F.lit(a) * u + v)


def outer(x: Column) -> Column:
    return F.flatten(F.transform(x, lambda u: F.transform(x, lambda v: u * v)))


def clip(v: Column, low: float = 0.0, high: float = 1.0) -> Column:
    """Into [low, high]; null and NaN become low. The value stands once in the expression, so a costly one is computed once."""
    return F.greatest(F.lit(low), F.least(F.lit(high), F.coalesce(F.nanvl(v.cast("double"), F.lit(low)), F.lit(low))))


def clip_ball(x: Column, radius: float = 1.0) -> Column:
    """Shrunk row by row into the ball; data-independent, so it keeps the privacy proof."""
    n = norm2(x)
    return F.transform(x, lambda v: v.cast("double") * F.when(n > radius, F.lit(radius) / n).otherwise(F.lit(1.0)))
