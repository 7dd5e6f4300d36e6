"""Lifts that turn inner-product order into distance order, and power-norm maps."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from innersearch.functions import vectors as V


def lift_point(v: Column, bound2: Column | float) -> Column:
    """v with the coordinate that brings its squared norm to bound2."""
    return F.concat(v, F.array(F.sqrt(F.greatest(F.lit(0.0), bound2 - V.sq(v)))))


def lift_query(q: Column, bound2: Column | float) -> Column:
    """q scaled to the norm sqrt(bound2), with a zero coordinate."""
    return F.concat(V.scale(q, F.sqrt(F.lit(bound2) if not isinstance(bound2, Column) else bound2) / V.l2(q)), F.array(F.lit(0.0)))


def unit_lift_point(v: Column, bound: Column) -> Column:
    """v / bound with the coordinate that makes it a unit vector."""
    s = V.scale(v, F.lit(1.0) / bound)
    return F.concat(s, F.array(F.sqrt(F.greatest(F.lit(0.0), 1 - V.sq(s)))))


def power_point(v: Column, powers: int) -> Column:
    """v followed by |v|^2, |v|^4, ... ."""
    n2 = V.sq(v)
    return F.concat(v, F.array(*[F.pow(n2, F.lit(float(2**i))) for i in range(powers)]))


def power_query(q: Column, powers: int) -> Column:
    return F.concat(V.normalize(q), F.array(*[F.lit(0.5)] * powers))
