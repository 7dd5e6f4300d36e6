"""Lloyd's k-means: fitted on a bounded sample, assigned to all rows by literal centres."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.functions import vectors as V

#: Most rows of the sample that centres are fitted on.
SAMPLE_ROWS = 1_000_000


def hash_share(key: str) -> Column:
    """A number in [0, 1) from a hash of the key, in steps of 2^-53: a sample at any rate keeps its number of rows."""
    return F.shiftrightunsigned(F.xxhash64(key), 11).cast("double") / float(2**53)


def nearest(v: str, centres) -> Column:
    """struct(d, part): distance and index of the nearest centre, ties to the smaller index."""
    return F.array_min(F.array(*[F.struct(V.dist(F.col(v), V.literal(c)).alias("d"), F.lit(i).alias("part")) for i, c in enumerate(centres)]))


def first_centres(df: DataFrame, v: str, k: int, key: str = "vec_id") -> list[list[float]]:
    return [list(r[0]) for r in df.orderBy(F.md5(F.col(key).cast("string")), key).select(v).limit(k).collect()]


def lloyd(df: DataFrame, v: str, k: int, iters: int = 8, key: str = "vec_id") -> tuple[list[list[float]], list[float]]:
    """Centres, and the inertia before each round.  k rows reach the driver each round."""
    n = df.count()
    sample = df.select(key, v) if n <= SAMPLE_ROWS else df.select(key, v).where(hash_share(key) < SAMPLE_ROWS / n)
    sample = sample.persist()
    centres, inertia = first_centres(sample, v, k, key), []
    if not centres:
        return [], []
    d = len(centres[0])
    for _ in range(iters):
        near = sample.withColumn("near", nearest(v, centres))
        sums = [F.avg(F.col(v)[i]).alias(f"c{i}") for i in range(d)]
        rows = near.groupBy(F.col("near.part").alias("part")).agg(F.sum(F.col("near.d") * F.col("near.d")).alias("ss"), *sums).collect()
        inertia.append(sum(r["ss"] for r in rows))
        moved = [list(c) for c in centres]
        for r in rows:
            moved[r["part"]] = [r[f"c{i}"] for i in range(d)]
        if all(math.isclose(a, b, abs_tol=1e-12) for x, y in zip(moved, centres, strict=True) for a, b in zip(x, y, strict=True)):
            break
        centres = moved
    sample.unpersist()
    return centres, inertia
