"""Ball search: everything within a projected radius, certificates, and one enlargement."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators import certificates as C
from innersearch.operators.exact import spread, top_k
from innersearch.sources import scratch

STATS = ("qid", "n_candidates", "radius", "radius_final", "stop_reason")


def in_ball(points: DataFrame, balls: DataFrame, exclude_self: bool = True) -> DataFrame:
    """qid, vec_id, pdist, ip of points with lo < pdist <= hi; balls(qid, qv, qpv, lo, hi) is broadcast.

    The filter on the narrow projection stands below the inner product."""
    both = spread(points.select("vec_id", "v", "pv")).crossJoin(F.broadcast(balls))
    if exclude_self:
        both = both.where("vec_id != qid")
    near = both.withColumn("pdist", V.dist("pv", "qpv")).where("pdist <= hi and pdist > lo")
    return near.select("qid", "vec_id", "pdist", V.dot("v", "qv").alias("ip"))


def first_pass(points: DataFrame, queries: DataFrame, radii: DataFrame, exclude_self: bool = True, fetch=in_ball) -> DataFrame:
    """Candidates of the closed balls of radii(qid, radius)."""
    balls = queries.join(F.broadcast(radii.select("qid", "radius")), "qid").select("qid", "qv", "qpv", F.lit(-1.0).alias("lo"), F.col("radius").alias("hi"))
    return fetch(points, balls, exclude_self)


def verdict(found: DataFrame, queries: DataFrame, radii: DataFrame, maxn2: float, k: int, c: float, chi: float) -> DataFrame:
    """qid, n_candidates, kth, radius, cert_a, cert_b, radius_next of each query after a pass."""
    per = top_k(found, k).groupBy("qid").agg(F.min("ip").alias("least"), F.count("*").alias("got"))
    counts = found.groupBy("qid").agg(F.count("*").alias("n_candidates"))
    q = queries.select("qid", "qn2").join(radii.select("qid", "radius"), "qid").join(per, "qid", "left").join(counts, "qid", "left")
    q = q.withColumn("kth", F.when(F.col("got") >= k, F.col("least")))
    a = C.max_norm_ok(F.col("kth"), F.col("qn2"), maxn2, c)
    b = C.chi_ok(F.col("radius"), F.col("kth"), F.col("qn2"), maxn2, c, chi)
    nxt = F.when(F.col("kth").isNull(), F.lit(None).cast("double")).otherwise(C.enlarged(F.col("radius"), F.col("kth"), F.col("qn2"), maxn2, c, chi))
    return q.select("qid", F.coalesce("n_candidates", F.lit(0)).alias("n_candidates"), "kth", "radius", a.alias("cert_a"), b.alias("cert_b"), nxt.alias("radius_next"))


def kth_near(points: DataFrame, queries: DataFrame, k: int, exclude_self: bool = True, fetch=in_ball, enclosing=None) -> DataFrame:
    """qid, radius: the projected distance of the k-th nearest projected neighbour (the greatest if there are fewer).

    An index gives a radius that holds k points (`enclosing`); without it all points are looked at."""
    balls = queries.select("qid", "qv", "qpv", F.lit(-1.0).alias("lo"), F.lit(float("inf")).alias("hi"))
    if enclosing is not None:
        reach = enclosing(queries)
        balls = balls.join(F.broadcast(reach), "qid").withColumn("hi", F.coalesce("reach", "hi")).drop("reach")
    near = fetch(points, balls, exclude_self).select("qid", "vec_id", (-F.col("pdist")).alias("near"))
    return top_k(near, k, "near").groupBy("qid").agg(F.max(-F.col("near")).alias("radius"))


def ball_search(points: DataFrame, queries: DataFrame, radii: DataFrame, maxn2: float, k: int, c: float, chi: float, compensate: bool = True, exclude_self: bool = True, fetch=in_ball, enclosing=None) -> tuple[DataFrame, DataFrame]:
    """hits(qid, rank, vec_id, ip) and stats(qid, n_candidates, radius, radius_final, stop_reason).

    Queries that found fewer than k points get a radius that holds k; uncertified ones get the annulus up to the
    enlarged radius in one more pass.  What a pass found is written: ids and products, no vectors."""
    q = queries.select("qid", "qv", "qpv", "qn2")
    found = scratch.written(first_pass(points, q, radii, exclude_self, fetch), "found")
    first = scratch.written(verdict(found, q, radii, maxn2, k, c, chi), "verdict")
    short = first.where("kth is null").select("qid")
    base = radii.select("qid", "radius")
    if compensate and not short.isEmpty():
        wider = kth_near(points, q.join(F.broadcast(short), "qid", "left_semi"), k, exclude_self, fetch, enclosing)
        base = base.join(F.broadcast(wider.withColumnRenamed("radius", "wide")), "qid", "left").select("qid", F.greatest("radius", F.coalesce("wide", F.lit(0.0))).alias("radius"))
        base = scratch.written(base, "base")
        grown = first_pass(points, q.join(F.broadcast(short), "qid", "left_semi"), base, exclude_self, fetch)
        found = scratch.written(found.join(F.broadcast(short), "qid", "left_anti").unionByName(grown), "found")
        first = scratch.written(verdict(found, q, base, maxn2, k, c, chi), "verdict")
    best = top_k(found, k)
    if compensate:
        open_ = first.where("not cert_a and not cert_b and radius_next > radius").select("qid", F.col("radius").alias("lo"), F.col("radius_next").alias("hi"))
        ring = fetch(points, q.join(F.broadcast(open_), "qid").select("qid", "qv", "qpv", "lo", "hi"), exclude_self)
        ring = scratch.written(ring, "annulus")
        best = top_k(best.select("qid", "vec_id", "ip").unionByName(ring.select("qid", "vec_id", "ip")), k)
        extra = ring.groupBy("qid").agg(F.count("*").alias("extra"))
        first = first.join(extra, "qid", "left").withColumn("n_candidates", F.col("n_candidates") + F.coalesce("extra", F.lit(0)))
    reason = F.when(F.col("cert_a"), "A").when(F.col("cert_b"), "B").when(F.lit(compensate) & F.col("kth").isNotNull(), "extended").otherwise("exhausted")
    start = radii.select("qid", F.col("radius").alias("radius0"))
    final = F.when(F.col("cert_a") | F.col("cert_b") | F.lit(not compensate), F.col("radius")).otherwise(F.coalesce("radius_next", "radius"))
    stats = first.join(start, "qid").select("qid", "n_candidates", F.col("radius0").alias("radius"), final.alias("radius_final"), reason.alias("stop_reason"))
    return best, stats


def banded_search(points: DataFrame, queries: DataFrame, radii: DataFrame, k: int, c: float, chi: float, exclude_self: bool = True) -> tuple[DataFrame, DataFrame]:
    """hits and stats(qid, n_candidates, radius, n_bands) with a certificate for each band of norms; points have a `band`.

    The greatest norm of a band stands in for that of all points: after the first ball a band needs no more where its max-norm
    certificate holds, else its points up to the radius at which its chi-square certificate does.  Each unread point is so
    covered by the certificate of its own band, at the same probability.  Bands of small norms are read less far or not at
    all.  A query short of k points reads every band whole."""
    q = queries.select("qid", "qv", "qpv", "qn2")
    narrow = points.select("vec_id", "v", "pv", "band")
    found = scratch.written(first_pass(points, q, radii, exclude_self), "found")
    bands = points.groupBy("band").agg(F.max("n2").alias("top"))
    first = scratch.written(verdict(found, q, radii, 0.0, k, c, chi).select("qid", "n_candidates", "kth", "radius"), "verdict")
    both = first.join(q, "qid").crossJoin(F.broadcast(bands))
    need = F.when(F.col("kth").isNull(), F.lit(float("inf"))).otherwise(C.enlarged(F.lit(0.0), F.col("kth"), F.col("qn2"), F.col("top"), c, chi))
    asked = scratch.written(both.withColumn("hi", need).where("hi > radius").select("qid", "qv", "qpv", "band", F.col("radius").alias("lo"), "hi"), "band_balls")
    met = spread(narrow).join(F.broadcast(asked), "band")
    if exclude_self:
        met = met.where("vec_id != qid")
    more = met.withColumn("pdist", V.dist("pv", "qpv")).where("pdist <= hi and pdist > lo").select("qid", "vec_id", V.dot("v", "qv").alias("ip"))
    more = scratch.written(more, "annulus")
    extra = more.groupBy("qid").agg(F.count("*").alias("extra"))
    open_ = asked.groupBy("qid").agg(F.count("*").alias("n_bands"))
    stats = first.join(extra, "qid", "left").join(open_, "qid", "left")
    best = top_k(found.select("qid", "vec_id", "ip").unionByName(more), k)
    return best, stats.select("qid", (F.col("n_candidates") + F.coalesce("extra", F.lit(0))).alias("n_candidates"), "radius", F.coalesce("n_bands", F.lit(0)).alias("n_bands"))


def verified(found: DataFrame, queries: DataFrame, maxn2: float, k: int, c: float) -> DataFrame:
    """qid, n_verified: candidates compared, in distance order, until the max-norm certificate holds on the best
    (k = 1), or all of them."""
    from pyspark.sql import Window

    if k != 1:
        raise ValueError("the running best is a window for k = 1 only")
    w = Window.partitionBy("qid").orderBy("pdist", "vec_id")
    steps = found.join(F.broadcast(queries.select("qid", "qn2")), "qid").withColumn("rn", F.row_number().over(w)).withColumn("best", F.max("ip").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    hit = F.min(F.when(C.max_norm_ok(F.col("best"), F.col("qn2"), maxn2, c), F.col("rn")))
    return steps.groupBy("qid").agg(F.coalesce(hit, F.max("rn")).cast("long").alias("n_verified"))
