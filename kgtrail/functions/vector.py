"""Vector arithmetic over arrays, as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def sign_code(v: Column, planes: list[list[float]]) -> Column:
    """One bit for each hyperplane, as text: the side on which v lies."""
    return F.concat(*[F.when(dot(v, F.array(*[F.lit(float(x)) for x in p])) >= 0, "1").otherwise("0") for p in planes])
