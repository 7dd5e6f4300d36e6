"""Stepwise search: projected neighbours nearest first, both stop rules at each step."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators import certificates as C
from innersearch.operators.exact import spread, top_k


def pairs_of(points: DataFrame, queries: DataFrame, exclude_self: bool = True) -> DataFrame:
    """qid, vec_id, pdist, ip, qn2 of projected points and projected queries (broadcast)."""
    both = spread(points.select("vec_id", "v", "pv")).crossJoin(F.broadcast(queries))
    if exclude_self:
        both = both.where("vec_id != qid")
    return both.select("qid", "vec_id", V.dist("pv", "qpv").alias("pdist"), V.dot("v", "qv").alias("ip"), "qn2")


def stops_k1(pairs: DataFrame, maxn2: float, c: float, chi: float, rules: str = "AB") -> DataFrame:
    """qid, stop (rank of the first step at which a rule holds, or the number of points), reason."""
    w = Window.partitionBy("qid").orderBy("pdist", "vec_id")
    steps = pairs.withColumn("rn", F.row_number().over(w)).withColumn("best", F.max("ip").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    a = C.max_norm_ok(F.col("best"), F.col("qn2"), maxn2, c) if "A" in rules else F.lit(False)
    b = C.chi_ok(F.col("pdist"), F.col("best"), F.col("qn2"), maxn2, c, chi) if "B" in rules else F.lit(False)
    hit = F.when(a, F.struct("rn", F.lit("A").alias("reason"))).when(b, F.struct("rn", F.lit("B").alias("reason")))
    out = steps.groupBy("qid").agg(F.min(hit).alias("hit"), F.max("rn").alias("n"))
    return out.select("qid", F.coalesce("hit.rn", "n").alias("stop"), F.coalesce("hit.reason", F.lit("exhausted")).alias("reason"))


def stepwise_k1(pairs: DataFrame, maxn2: float, c: float, chi: float, rules: str = "AB") -> DataFrame:
    """qid, vec_id, ip, stop, reason: the best of the prefix at which the search stops."""
    stops = stops_k1(pairs, maxn2, c, chi, rules)
    w = Window.partitionBy("qid").orderBy("pdist", "vec_id")
    prefix = pairs.withColumn("rn", F.row_number().over(w)).join(stops, "qid").where("rn <= stop")
    return top_k(prefix, 1, keep=("stop", "reason")).drop("rank")


def stepwise(pairs: DataFrame, maxn2: float, k: int, c: float, chi: float, rules: str = "AB") -> DataFrame:
    """qid, rank, vec_id, ip, stop, reason for k answers.

    The running k-th best needs a heap: a grouped scan whose group is one query's ordered candidates."""

    def scan(pdf):
        import pandas as pd

        pdf = pdf.sort_values(["pdist", "vec_id"])
        heap, reason, stop = [], "exhausted", len(pdf)
        for i, (vec, pd_, ip, qn2) in enumerate(zip(pdf["vec_id"], pdf["pdist"], pdf["ip"], pdf["qn2"], strict=True), 1):
            item = (ip, -vec)
            if len(heap) < k:
                heapq.heappush(heap, item)
            elif item > heap[0]:
                heapq.heapreplace(heap, item)
            if len(heap) < k:
                continue
            m = maxn2 + qn2 - 2 * heap[0][0] / c
            if ("A" in rules and m <= 0) or ("B" in rules and m > 0 and pd_ * pd_ >= chi * m):
                reason, stop = ("A" if m <= 0 else "B"), i
                break
        best = sorted(heap, reverse=True)
        return pd.DataFrame({"qid": pdf["qid"].iloc[0], "rank": range(1, len(best) + 1), "vec_id": [-v for _, v in best], "ip": [x for x, _ in best], "stop": stop, "reason": reason})

    return pairs.groupBy("qid").applyInPandas(scan, "qid long, rank int, vec_id long, ip double, stop int, reason string")


def stepwise_waves(points: DataFrame, queries: DataFrame, radii: DataFrame, maxn2: float, k: int, c: float, chi: float, waves: int = 12) -> DataFrame:
    """The same answers without ordering all points: balls of doubling radius from radii(qid, radius).

    A wave hands the grouped scan only the points of its balls, and only of queries that have not stopped;
    `stop` is exact because a ball holds a prefix of the order.  The last wave takes everything."""
    done, left = None, queries.join(F.broadcast(radii.select("qid", "radius")), "qid")
    for i in range(waves):
        last = i == waves - 1
        q = left.withColumn("r", F.col("radius") * 2.0**i)
        near = pairs_of(points, q.select("qid", "qv", "qpv", "qn2")) if last else _within(points, q)
        found = stepwise(near, maxn2, k, c, chi).persist()
        stopped = found if last else found.where("reason != 'exhausted'")
        done = stopped if done is None else done.unionByName(stopped)
        left = left.join(F.broadcast(stopped.select("qid").distinct()), "qid", "left_anti")
        if last or left.isEmpty():
            return done
    return done


def _within(points: DataFrame, q: DataFrame) -> DataFrame:
    both = spread(points.select("vec_id", "v", "pv")).crossJoin(F.broadcast(q)).where("vec_id != qid").withColumn("pdist", V.dist("pv", "qpv")).where("pdist <= r")
    return both.select("qid", "vec_id", "pdist", V.dot("v", "qv").alias("ip"), "qn2")


def nearest_euclid(pairs: DataFrame, k: int, c: float, chi: float) -> DataFrame:
    """Euclidean neighbours by projected order: stops when the projected distance, over the chi-square quantile,
    exceeds the k-th best true distance by the factor c.  pairs has qid, vec_id, pdist and d2 (squared distance)."""

    def scan(pdf):
        import pandas as pd

        pdf = pdf.sort_values(["pdist", "vec_id"])
        heap, stop = [], len(pdf)
        for i, (vec, p, d2) in enumerate(zip(pdf["vec_id"], pdf["pdist"], pdf["d2"], strict=True), 1):
            heapq.heappush(heap, (-d2, -vec))
            if len(heap) > k:
                heapq.heappop(heap)
            if len(heap) == k and p * p >= chi * -heap[0][0] * c * c:
                stop = i
                break
        best = sorted((-d, -v) for d, v in heap)
        return pd.DataFrame({"qid": pdf["qid"].iloc[0], "rank": range(1, len(best) + 1), "vec_id": [v for _, v in best], "dist": [max(0.0, d) ** 0.5 for d, _ in best], "stop": stop})

    return pairs.groupBy("qid").applyInPandas(scan, "qid long, rank int, vec_id long, dist double, stop int")
