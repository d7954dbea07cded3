"""Vector arithmetic as column expressions that stay in generated code; sums run in order, so engines agree to the last bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_ZERO = F.lit


def _d(x: Column) -> Column:
    return F.transform(x, lambda v: v.cast("double"))


def inner(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(_d(x), _d(y), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def l2_squared(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(_d(x), _d(y), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)


def l2(x: Column, y: Column) -> Column:
    return F.sqrt(l2_squared(x, y))


def norm(x: Column) -> Column:
    return F.sqrt(inner(x, x))


def cosine(x: Column, y: Column) -> Column:
    return inner(x, y) / (norm(x) * norm(y))


def normalise(x: Column) -> Column:
    return F.transform(_d(x), lambda v: v / norm(x))
