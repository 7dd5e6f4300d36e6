"""The whole job beside the catalogue's queries whose SQL holds them to id subsets: all rows, no id filter."""

from __future__ import annotations

import copy
import functools
import math
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators import certificates, exact, metrics, pages, projection, ringindex
from innersearch.plans import engine
from innersearch.plans import oracles as O
from innersearch.plans.catalog import C, CHI, K, M, MATRIX, Setup, hits6, q, r6
from innersearch.sources import vectors as S

#: Every row whose id is divisible by EVERY is a query.
EVERY = 50
#: Queries of one pass over the points (on average, by a hash of qid), and rows of one side of a block of pairs.
QUERY_BLOCK, PAIR_BLOCK, SLICE = 512, 4096, 1024


#: The query set and its pairs with all points, as SQL.
PAIRS_SQL = f"WITH p AS ({O.SOURCES['unit']}), pr AS MATERIALIZED (SELECT a.vec_id AS qid, p.vec_id, a.v AS qv, p.v FROM p, p a WHERE a.vec_id % {EVERY} = 0 AND p.vec_id <> a.vec_id)"
DOTS_SQL = f"{PAIRS_SQL} SELECT qid, vec_id, round(list_dot_product(v, qv), 6) AS ip FROM pr"


def query_set(points: DataFrame) -> DataFrame:
    return points.where(F.col("vec_id") % EVERY == 0).select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))


def hashed_blocks(rows: DataFrame, key: str, size: int) -> list[DataFrame]:
    """rows in parts of about `size` rows."""
    parts = max(1, math.ceil(rows.count() / size))
    at = F.pmod(F.xxhash64(key), F.lit(parts))
    return [rows.where(at == j) for j in range(parts)]


def union(frames: list[DataFrame]) -> DataFrame:
    return functools.reduce(DataFrame.unionByName, frames)


def in_blocks(x: Setup, f: Callable[[Setup], DataFrame]) -> DataFrame:
    """f of the setup with each block of the query set: one pass over the points for each."""
    out = []
    for block in hashed_blocks(query_set(x.raw), "qid", QUERY_BLOCK):
        y = copy.copy(x)  # keeps what is cached of the points
        y.queries = projection.project_queries(block, MATRIX)
        out.append(f(y))
    return union(out)


def pairs_above(points: DataFrame, least: float, size: int = PAIR_BLOCK) -> DataFrame:
    """a, b of all pairs a < b whose product, rounded to 9 digits, is above `least`: blocks of b are sent to the tasks one by one."""
    import numpy as np

    def above(shared):
        def run(batches):
            import pyarrow as pa

            ids, m = shared.value
            for batch in batches:
                for at in range(0, batch.num_rows, SLICE):
                    x = batch.slice(at, SLICE)
                    a = x.column(0).to_numpy()
                    ip = x.column(1).flatten().to_numpy().reshape(x.num_rows, -1) @ m.T
                    i, j = np.nonzero((np.round(ip, 9) > least) & (a[:, None] < ids[None, :]))
                    yield pa.RecordBatch.from_arrays([pa.array(a[i]), pa.array(ids[j])], names=["a", "b"])

        return run

    out, points = [], points.select("vec_id", "v")
    for block in hashed_blocks(points, "vec_id", size):
        rows = block.toArrow()
        if rows.num_rows:
            ids, v = rows["vec_id"].to_numpy(), rows["v"].combine_chunks().flatten().to_numpy().reshape(rows.num_rows, -1)
            out.append(points.mapInArrow(above(points.sparkSession.sparkContext.broadcast((ids, v))), "a long, b long"))
    return union(out) if out else points.sparkSession.createDataFrame([], "a long, b long")


@q("heavy_pairs_all")
def _(s, d):
    return pairs_above(S.unit_embeddings(s, d), 0.3)


@q("pair_dots_all", DOTS_SQL)
def _(s, d):
    return in_blocks(Setup(s, d), lambda x: x.pairs.select("qid", "vec_id", r6("ip")))


@q("distance_identity_all", f"{PAIRS_SQL} SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 5) AS d2 FROM pr")
def _(s, d):
    def one(x):
        both = x.raw.crossJoin(F.broadcast(x.queries.select("qid", "qv"))).where("vec_id != qid")
        return both.select("qid", "vec_id", F.round(V.dist2("v", "qv"), 5).alias("d2"))

    return in_blocks(Setup(s, d), one)


@q("certificate_b_all")
def _(s, d):
    x = Setup(s, d)
    top = x.maxn2
    return in_blocks(x, lambda y: y.pairs.select("qid", "vec_id", certificates.chi_ok(F.col("pdist"), F.col("ip"), F.col("qn2"), top, C, CHI).alias("holds")))


@q("sql_functions_all", DOTS_SQL)
def _(s, d):
    from innersearch.operators import sqlsurface

    sqlsurface.register(s)

    def one(x):
        text = "SELECT /*+ BROADCAST(b) */ qid, vec_id, round(inner_product(v, qv), 6) AS ip FROM {a} a, {b} b WHERE vec_id <> qid"
        return s.sql(text, a=x.raw, b=x.queries.select("qid", "qv"))

    return in_blocks(Setup(s, d), one)


@q("posexplode_dots_all", DOTS_SQL)
def _(s, d):
    def one(x):
        p = x.raw.select("vec_id", F.posexplode("v").alias("j", "a"))
        qs = x.queries.select("qid", F.posexplode("qv").alias("j", "b"))
        return p.join(F.broadcast(qs), "j").where("vec_id != qid").groupBy("qid", "vec_id").agg(F.round(F.sum(F.col("a") * F.col("b")), 6).alias("ip"))

    return in_blocks(Setup(s, d), one)


@q("page_access_all")
def _(s, d):
    x = Setup(s, d)
    index, size = x.plain, pages.row_bytes(len(MATRIX[0]))

    def one(y):
        balls = y.queries.join(y.radii, "qid").select("qid", "qpv", F.lit(-1.0).alias("lo"), F.col("radius").alias("hi"))
        return pages.page_access(ringindex.candidate_cells(index, balls), index.subcells, size)

    return in_blocks(x, one)


# ---- searches on the whole query set


def exact_all(x: Setup, k: int) -> DataFrame:
    return union([exact.exact_topk_blocked(x.raw, block, k) for block in hashed_blocks(query_set(x.raw), "qid", QUERY_BLOCK)])


@q("exact_topk_all", f"{PAIRS_SQL} SELECT qid, CAST(rn AS INTEGER) AS rank, vec_id, round(ip, 6) AS ip FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY ip DESC, vec_id) AS rn FROM (SELECT qid, vec_id, list_dot_product(v, qv) AS ip FROM pr)) WHERE rn <= {K}")
def _(s, d):
    return hits6(exact_all(Setup(s, d), K))


@q("ball_topk_all")
def _(s, d):
    x = Setup(s, d)
    x.maxn2  # noqa: B018  once, not for each block
    return hits6(in_blocks(x, lambda y: y.ball()[0]))


@q("flagship_search_all")
def _(s, d):
    points = S.label_clustered(s, d)
    e = engine.build(points, engine.SearchParams(m=M))
    return hits6(union([e.search(block)[0] for block in hashed_blocks(query_set(points), "qid", QUERY_BLOCK)]))


@q("recall_all")
def _(s, d):
    """Recall of each query against the exact answers, by source."""
    out = []
    for source in ("unit", "skewed", "clustered"):
        x = Setup(s, d, source)
        x.maxn2  # noqa: B018
        out.append(metrics.recall(in_blocks(x, lambda y: y.ball()[0]), exact_all(x, K)).select(F.lit(source).alias("source"), "qid", r6("recall")))
    return union(out)
