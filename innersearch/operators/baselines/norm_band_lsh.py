"""Norm-band LSH: equal-count bands by norm, sign codes of a unit lift, one multi-probed bucket table."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from innersearch.functions import transforms
from innersearch.functions import vectors as V
from innersearch.operators.exact import ranked, top_k
from innersearch.operators.projection import gaussian_matrix, projected
from innersearch.operators.signcells import sign_code

BANDS, BITS, EPSILON = 32, 11, 0.1


def bands(points: DataFrame, n_bands: int = BANDS) -> DataFrame:
    """points with n2 and band (1 has the greatest norms); the first n mod n_bands bands have a point more."""
    placed, n = ranked(points.withColumn("n2", F.round(V.sq("v"), 12)), [F.desc("n2"), F.col("vec_id")])
    size, more = divmod(n, n_bands)
    at = F.col("place")
    rest = F.floor((at - more * (size + 1)) / max(1, size)) + more
    band = F.when(at < more * (size + 1), F.floor(at / (size + 1))).otherwise(rest) + 1
    return placed.withColumn("band", band.cast("int")).drop("place")


def build(points: DataFrame, d: int, n_bands: int = BANDS, bits: int = BITS, seed: int = 42) -> DataFrame:
    """vec_id, v, band, bound (greatest norm of the band), code."""
    w = gaussian_matrix(bits, d + 1, seed)
    b = bands(points, n_bands)
    bound = b.groupBy("band").agg(F.sqrt(F.max("n2")).alias("bound"))
    lifted = b.join(F.broadcast(bound), "band").withColumn("u", transforms.unit_lift_point(F.col("v"), F.greatest(F.col("bound"), F.lit(1e-12))))
    return lifted.withColumn("uw", projected("u", w)).select("vec_id", "v", "band", "bound", sign_code("uw", bits).alias("code"))


def probe_order(index: DataFrame, queries: DataFrame, d: int, bits: int = BITS, seed: int = 42) -> DataFrame:
    """qid, band, code, cnt, score: buckets by the product they promise, bound * cos(pi (1-e)(1 - matches/bits))."""
    w = gaussian_matrix(bits, d + 1, seed)
    q = queries.withColumn("qu", F.concat(V.normalize("qv"), F.array(F.lit(0.0)))).withColumn("quw", projected("qu", w)).select("qid", sign_code("quw", bits).alias("qcode"))
    buckets = index.groupBy("band", "bound", "code").agg(F.count("*").alias("cnt"))
    both = q.crossJoin(F.broadcast(buckets))
    matches = bits - F.bit_count(F.col("code").bitwiseXOR(F.col("qcode")))
    score = F.round(F.col("bound") * F.cos(math.pi * (1 - EPSILON) * (1 - matches / bits)), 9)
    return both.select("qid", "band", "code", "cnt", score.alias("score"))


def reads(index: DataFrame, queries: DataFrame, d: int, budget: int | None = None, bits: int = BITS, seed: int = 42) -> DataFrame:
    """qid, vec_id, ip of the points in the best buckets until `budget` points are read (the bucket that crosses it is read whole); the default is
    a tenth of the points, at least 200."""
    budget = budget or max(200, math.ceil(index.count() / 10))
    order = probe_order(index, queries, d, bits, seed)
    w = Window.partitionBy("qid").orderBy(F.desc("score"), "band", "code").rowsBetween(Window.unboundedPreceding, -1)
    chosen = order.withColumn("before", F.coalesce(F.sum("cnt").over(w), F.lit(0))).where(F.col("before") < budget).select("qid", "band", "code")
    got = index.join(F.broadcast(chosen), ["band", "code"]).join(F.broadcast(queries.select("qid", "qv")), "qid").where("vec_id != qid")
    return got.select("qid", "vec_id", V.dot("v", "qv").alias("ip"))


def search(index: DataFrame, queries: DataFrame, d: int, k: int = 10, budget: int | None = None, bits: int = BITS, seed: int = 42) -> DataFrame:
    """hits among the points read."""
    return top_k(reads(index, queries, d, budget, bits, seed), k)
