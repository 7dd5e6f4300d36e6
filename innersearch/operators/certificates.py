"""The two stop rules as column predicates.

With slack c and best inner product b so far (the k-th best for k answers), the margin is
maxn2 + |q|^2 - 2 b / c.  The max-norm certificate holds when it is not positive; the chi-square
certificate when the squared projected distance reaches the chi-square quantile times a positive margin."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def margin(best: Column, qn2: Column, maxn2: Column | float, c: float) -> Column:
    return (F.lit(maxn2) if not isinstance(maxn2, Column) else maxn2) + qn2 - 2 * best / c


def max_norm_ok(best: Column, qn2: Column, maxn2: Column | float, c: float) -> Column:
    return F.coalesce(margin(best, qn2, maxn2, c) <= 0, F.lit(False))


def chi_ok(pdist: Column, best: Column, qn2: Column, maxn2: Column | float, c: float, chi: float) -> Column:
    m = margin(best, qn2, maxn2, c)
    return F.coalesce((m > 0) & (pdist * pdist >= chi * m), F.lit(False))


def enlarged(radius: Column, best: Column, qn2: Column, maxn2: Column | float, c: float, chi: float) -> Column:
    """The radius at which the chi-square certificate holds for the given best."""
    return F.greatest(radius, F.round(F.sqrt(chi * F.greatest(F.lit(0.0), margin(best, qn2, maxn2, c))), 9))


def max_norm(points: DataFrame) -> float:
    """Largest squared norm of projected points: one number kept with an index."""
    return float(points.agg(F.max("n2")).first()[0] or 0.0)
