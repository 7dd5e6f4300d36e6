"""Vector expressions on array<double> columns (JVM side)."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def literal(values: Sequence[float]) -> Column:
    return F.expr(f"array({', '.join(f'{float(x)!r}D' for x in values)})")


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def l1(a: Column | str) -> Column:
    return F.aggregate(_col(a), F.lit(0.0), lambda s, x: s + F.abs(x))


def sq(a: Column | str) -> Column:
    return F.aggregate(_col(a), F.lit(0.0), lambda s, x: s + x * x)


def l2(a: Column | str) -> Column:
    return F.sqrt(sq(a))


def dist2(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def dist(a: Column | str, b: Column | str) -> Column:
    """Distance rounded to 9 digits, so that membership does not hang on the order of summation."""
    return F.round(F.sqrt(dist2(a, b)), 9)


def scale(a: Column | str, by: Column | float) -> Column:
    return F.transform(_col(a), lambda x: x * by)


def plus(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def normalize(a: Column | str) -> Column:
    return scale(a, F.try_divide(F.lit(1.0), l2(a)))


def cosine(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(dot(a, b), l2(a) * l2(b))


def as_double(a: Column | str) -> Column:
    return _col(a).cast("array<double>")
