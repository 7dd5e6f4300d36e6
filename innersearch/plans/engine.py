"""The full method: project, probe a radius, search the ball on the ring index, certify, enlarge once."""

from __future__ import annotations

import dataclasses

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.functions import chisq
from innersearch.functions import vectors as V
from innersearch.operators import ball, certificates, pages, projection, ringindex, signcells
from innersearch.sources import scratch


@dataclasses.dataclass(frozen=True)
class SearchParams:
    k: int = 10
    c: float = 0.9
    p: float = 0.5
    m: int | None = None
    seed: int = 42
    exclude_self: bool = True
    lb_form: str = "l1"
    ub_norm: str = "l1"
    compensate: bool = True
    use_index: bool = True
    rescale_query: str = "none"
    page_bytes: int = pages.PAGE_BYTES
    target_rows: int = 64


@dataclasses.dataclass
class Engine:
    """A built index: projected points, sign cells, ring index and the constants of the plan."""

    params: SearchParams
    points: DataFrame
    cells: DataFrame
    ring: ringindex.RingIndex | None
    matrix: tuple
    d: int
    m: int
    n: int
    maxn2: float
    chi: float

    def queries(self, queries: DataFrame) -> DataFrame:
        """Projected queries; with rescale_query='max_norm' they get the norm at which certificate A fires easiest."""
        if self.params.rescale_query == "max_norm":
            queries = queries.withColumn("qv", V.scale("qv", F.lit(self.maxn2**0.5) / V.l2("qv")))
        return projection.project_queries(queries.select("qid", "qv"), self.matrix)

    def radii(self, queries: DataFrame, c: float | None = None, p: float | None = None) -> DataFrame:
        chi = self.chi if p is None else chisq.quantile(self.m, p)
        return signcells.radius_probe(self.cells, queries, self.m, c or self.params.c, chi, self.params.lb_form, self.params.ub_norm)

    def search(self, queries: DataFrame, k: int | None = None, c: float | None = None, p: float | None = None) -> tuple[DataFrame, DataFrame]:
        """hits(qid, rank, vec_id, ip) and stats(qid, n_candidates, radius, radius_final, stop_reason)."""
        x = self.params
        k, c = k or x.k, c or x.c
        chi = self.chi if p is None else chisq.quantile(self.m, p)
        q = scratch.written(self.queries(queries), "queries")
        radii = scratch.written(self.radii(q, c, p).select("qid", "radius"), "radii")
        fetch = ringindex.fetch(self.ring) if self.ring else ball.in_ball
        points = self.ring.points if self.ring else self.points
        near = (lambda some: ringindex.enclosing(self.ring, some, k, x.exclude_self)) if self.ring else None
        return ball.ball_search(points, q, radii, self.maxn2, k, c, chi, x.compensate, x.exclude_self, fetch, near)

    def page_access(self, queries: DataFrame, stats: DataFrame) -> DataFrame:
        """qid, pages (4 KB unless set otherwise) of the sub-cells that the final ball touches."""
        return pages.page_access(self.final_cells(queries, stats), self.ring.subcells, pages.row_bytes(self.d), self.params.page_bytes)

    def final_cells(self, queries: DataFrame, stats: DataFrame) -> DataFrame:
        """qid, part, ikey, sub of the sub-cells that the final ball touches."""
        q = self.queries(queries)
        balls = q.join(stats.select("qid", "radius_final"), "qid").select("qid", "qpv", F.lit(-1.0).alias("lo"), F.col("radius_final").alias("hi"))
        return ringindex.candidate_cells(self.ring, balls)


def build(points: DataFrame, params: SearchParams | None = None, path: str | None = None) -> Engine:
    """Projects the points, and writes them, their sign cells and the ring index under path (None: the shared folder).

    Nothing is cached: a search reads the written tables."""
    params = params or SearchParams()
    spark = points.sparkSession
    path = path or scratch.path_for(spark, "engine")
    n, d = points.agg(F.count("*"), F.max(F.size("v"))).first()
    m = params.m or signcells.best_dimension(n)
    matrix = projection.gaussian_matrix(m, d, params.seed)
    projection.project_points(points, matrix).write.parquet(f"{path}/projected")
    projected = spark.read.parquet(f"{path}/projected")
    signcells.build_cells(projected, m, "n1" if params.ub_norm == "l1" else "n2").coalesce(1).write.parquet(f"{path}/sign_cells")
    ring = None
    if params.use_index:
        k_p, n_key, k_sp = ringindex.params_for(n, params.target_rows)
        ring = ringindex.build(projected, k_p, n_key, k_sp, path=f"{path}/ring")
    cells = spark.read.parquet(f"{path}/sign_cells")
    return Engine(params, projected, cells, ring, matrix, d, m, n, certificates.max_norm(projected), chisq.quantile(m, params.p))
