"""SQL names for the expressions: scalar SQL functions (inlined by Catalyst) and table functions."""

from __future__ import annotations

import heapq
from itertools import combinations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

_SCALAR = {
    "inner_product(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, t) -> s + t)",
    "l1_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(a, 0D, (s, t) -> s + abs(t))",
    "l2_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(a, 0D, (s, t) -> s + t * t))",
}


def sign_neighbors_udtf():
    """The table function; its class is nested, so tasks get it by value: executors need not have this package."""

    @udtf(returnType="near: bigint")
    class SignNeighbors:
        """Codes of m bits that differ from a code in at most `radius` bits."""

        def eval(self, code: int, m: int, radius: int):
            for n in range(radius + 1):
                for bits in combinations(range(m), n):
                    near = code
                    for b in bits:
                        near ^= 1 << b
                    yield (near,)

    return SignNeighbors


def topk_heap(k: int):
    """A grouped aggregate of (product, id): the ids of the k greatest products, ties to the smaller id.

    The whole group reaches one Python worker; `exact.top_k` limits rows before the shuffle and is the way for large groups."""

    @pandas_udf("array<bigint>")
    def best(ip: pd.Series, vec_id: pd.Series) -> list[int]:
        return [-i for _, i in heapq.nlargest(k, zip(ip, -vec_id, strict=True))]

    return best


def register(spark: SparkSession) -> None:
    for head, body in _SCALAR.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("sign_neighbors", sign_neighbors_udtf())


def ball_search(spark: SparkSession, points: str, queries: str, k: int = 10, c: float = 0.9, p: float = 0.5):
    """The full search over two views, points(vec_id, v) and queries(qid, qv)."""
    from innersearch.plans import engine

    return engine.build(spark.table(points), engine.SearchParams(k=k, c=c, p=p)).search(spark.table(queries))[0]
