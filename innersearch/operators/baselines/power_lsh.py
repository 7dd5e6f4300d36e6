"""Asymmetric LSH with appended powers of the norm."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.functions import transforms
from innersearch.functions import vectors as V
from innersearch.operators.exact import top_k
from innersearch.operators.projection import gaussian_matrix, projected
from innersearch.sources import scratch


def search(points: DataFrame, queries: DataFrame, d: int, k: int = 10, powers: int = 3, shrink: float = 0.83, tables: int = 32, width: float = 1.0, seed: int = 42) -> DataFrame:
    """hits among points that share at least one of `tables` buckets with the query.

    Buckets are met by ids; vectors are read for the points met."""
    w = gaussian_matrix(tables, d + powers, seed)
    top = points.agg(F.max(V.l2("v")).alias("top"))
    p = points.crossJoin(F.broadcast(top)).withColumn("u", transforms.power_point(V.scale("v", F.lit(shrink) / F.col("top")), powers)).withColumn("h", projected("u", w))
    q = queries.withColumn("u", transforms.power_query(F.col("qv"), powers)).withColumn("h", projected("u", w))
    shift = [round((i * math.pi) % width, 6) for i in range(tables)]
    bucket = F.transform("h", lambda x, i: F.struct(i.alias("t"), F.floor((x + F.get(V.literal(shift), i)) / width).alias("b")))
    pb = p.select("vec_id", F.explode(bucket).alias("x")).select("vec_id", "x.*")
    qb = q.select("qid", F.explode(bucket).alias("x")).select("qid", "x.*")
    met = scratch.written(pb.join(F.broadcast(qb), ["t", "b"]).where("vec_id != qid").select("qid", "vec_id").distinct(), "met")
    both = points.join(scratch.small_side(met), "vec_id").join(F.broadcast(queries.select("qid", "qv")), "qid")
    return top_k(both.select("qid", "vec_id", V.dot("v", "qv").alias("ip")), k)
