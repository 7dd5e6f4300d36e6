"""Sign codes, their distance bounds, the radius probe and the choice of the projected dimension."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from innersearch.functions import vectors as V


def sign_code(pv: str, m: int) -> Column:
    """Bit i is set where coordinate i is not negative."""
    bits = [F.when(F.col(pv)[i] >= 0, F.lit(1 << i)).otherwise(F.lit(0)) for i in range(m)]
    code = bits[0]
    for b in bits[1:]:
        code = code + b
    return code.cast("long")


def _differing(code: Column, qcode: Column, qpv: Column) -> Column:
    """Coordinates of qpv at the bits where the codes differ."""
    x = code.bitwiseXOR(qcode)
    return F.filter(F.transform(qpv, lambda v, i: F.when(F.call_function("shiftright", x, i).bitwiseAND(F.lit(1).cast("long")) == 1, v)), lambda v: v.isNotNull())


def sign_lower_bound(code: Column, qcode: Column, qpv: Column, m: int, form: str = "l1") -> Column:
    """Least projected distance of a point with this code from the query.

    A point on the other side of a coordinate is at least that coordinate away.  'l1': sum over sqrt(m);
    'l2': the root of the sum of squares, never below it."""
    d = _differing(code, qcode, qpv)
    bound = V.l1(d) / math.sqrt(m) if form == "l1" else F.sqrt(V.sq(d))
    return F.round(bound, 9)


def norm_upper_bound(p: Column, q: Column) -> Column:
    """Greatest true distance from two norms (both 1-norms, or both 2-norms)."""
    return p + q


def build_cells(points: DataFrame, m: int, norm: str = "n1") -> DataFrame:
    """One row a code: the point of least norm (ties to the smaller id), its projection, and the count."""
    head = F.min_by(F.struct("vec_id", "pv", norm), F.struct(norm, "vec_id"))
    cells = points.withColumn("code", sign_code("pv", m)).groupBy("code").agg(head.alias("h"), F.count("*").alias("cnt"))
    return cells.select("code", F.col("h.vec_id").alias("head_id"), F.col(f"h.{norm}").alias("head_norm"), F.col("h.pv").alias("head_pv"), "cnt")


def radius_probe(cells: DataFrame, queries: DataFrame, m: int, c: float, chi: float, form: str = "l1", norm: str = "l1") -> DataFrame:
    """qid, anchor_id, radius, test_passed, cells_scanned.

    Cells in the order of their lower bound; the first whose squared bound, over c times the squared upper
    bound of its head, reaches the threshold gives the anchor, else the cell of the greatest value.  At most 2^m cells a
    query, joined by broadcast of the cells."""
    qnorm = F.col("qn1") if norm == "l1" else F.sqrt("qn2")
    head = F.col("head_norm") if norm == "l1" else F.sqrt("head_norm")
    both = queries.withColumn("qcode", sign_code("qpv", m)).crossJoin(F.broadcast(cells))
    lb = sign_lower_bound(F.col("code"), F.col("qcode"), F.col("qpv"), m, form)
    ub = norm_upper_bound(head, qnorm)
    both = both.select("qid", "code", "head_id", V.dist("head_pv", "qpv").alias("r"), lb.alias("lb"), F.round(F.coalesce(F.try_divide(lb * lb, c * ub * ub), F.lit(0.0)), 9).alias("value"))
    w = Window.partitionBy("qid").orderBy("lb", "code")
    both = both.withColumn("rn", F.row_number().over(w))
    first = F.min(F.when(F.col("value") >= chi, F.struct("rn", "head_id", "r")))
    best = F.max(F.struct("value", "lb", "code", "head_id", "r"))
    out = both.groupBy("qid").agg(first.alias("f"), best.alias("b"), F.max("rn").alias("n"))
    return out.select(
        "qid", F.coalesce("f.head_id", "b.head_id").alias("anchor_id"), F.coalesce("f.r", "b.r").alias("radius"), F.col("f").isNotNull().alias("test_passed"), F.coalesce("f.rn", "n").alias("cells_scanned")
    )


def dimension_cost(n: int, m: int) -> float:
    return 2**m * (m + 1) + n / 2**m


def best_dimension(n: int, most: int = 40) -> int:
    """The integer m that costs least for n points."""
    return min(range(1, most + 1), key=lambda m: dimension_cost(n, m))
