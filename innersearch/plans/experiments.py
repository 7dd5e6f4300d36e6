"""Experiment workloads: every frame is (source, method, param, k, measure, value)."""

from __future__ import annotations

import functools
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from innersearch.operators import exact, metrics, pages, signcells
from innersearch.operators.baselines import norm_band_lsh, residual_pq, shell_lsh
from innersearch.plans import engine
from innersearch.sources import scratch
from innersearch.sources import vectors as S

SOURCES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "unit": S.unit_embeddings, "skewed": S.skewed_embeddings, "clustered": S.label_clustered,
    "terms": S.term_vectors, "rows": S.lineitem_features, "latent": lambda s, d: S.latent_factors(s, d)[0],
}
METHODS = ("ring", "shell_lsh", "norm_band_lsh", "residual_pq")


def tidy(df: DataFrame, source: str, method: str, param: str, k: int, **measures: str) -> DataFrame:
    out = df.agg(*[F.expr(e).cast("double").alias(name) for name, e in measures.items()])
    cols = [F.struct(F.lit(name).alias("measure"), F.col(name).alias("value")) for name in measures]
    return out.select(F.lit(source).alias("source"), F.lit(method).alias("method"), F.lit(param).alias("param"), F.lit(k).alias("k"), F.explode(F.array(*cols)).alias("m")).select("source", "method", "param", "k", "m.*")


class Bench:
    """One source with its queries and exact answers; each method is built once and written, and a search reads its files."""

    def __init__(self, spark: SparkSession, sf_dir: str, source: str, nq: int = 20, params: engine.SearchParams | None = None, queries: DataFrame | None = None):
        self.spark, self.source = spark, source
        self.points = scratch.written(SOURCES[source](spark, sf_dir), "points")
        self.queries = scratch.written(S.sample_queries(self.points, nq) if queries is None else queries, "queries")
        self.params = params or engine.SearchParams()
        self.build_seconds: dict[str, float] = {}
        self.paths: dict[str, str] = {}
        self._built: dict[str, object] = {}
        self._kept: dict[object, DataFrame] = {}
        self.n, self.d = self.points.agg(F.count("*"), F.max(F.size("v"))).first()

    @functools.cached_property
    def exact(self) -> DataFrame:
        """The exact answers, made when they are first asked for: sizes and pages need none."""
        return scratch.written(exact.exact_topk_blocked(self.points, self.queries, 100), "exact")

    def built(self, method: str):
        if method not in self._built:
            path = self.paths[method] = scratch.path_for(self.spark, method)
            began = time.perf_counter()
            if method == "ring":
                made = engine.build(self.points, self.params, path)
            elif method == "residual_pq":
                book = residual_pq.train(self.points, self.d)
                made = book, self._write(residual_pq.encode(self.points, book), path)
            else:
                how = {"shell_lsh": shell_lsh, "norm_band_lsh": norm_band_lsh}[method]
                made = self._write(how.build(self.points, self.d), path)
            self.build_seconds[method] = time.perf_counter() - began
            self._built[method] = made
        return self._built[method]

    def _write(self, index: DataFrame, path: str) -> DataFrame:
        """Vectors apart from the rest, as every method reads them from their own pages."""
        index.drop("v").write.parquet(f"{path}/index")
        index.select("vec_id", "v").write.parquet(f"{path}/vectors")
        back = [self.spark.read.parquet(f"{path}/{x}") for x in ("index", "vectors")]
        return back[0].join(back[1], "vec_id")

    def reads(self, method: str, k: int) -> DataFrame:
        """qid, vec_id, ip of the points that a baseline reads."""
        b = self.built(method)
        if method == "shell_lsh":
            return shell_lsh.reads(b, self.queries, self.d, self.n, k)
        if method == "norm_band_lsh":
            return norm_band_lsh.reads(b, self.queries, self.d)
        return residual_pq.reads(b[1], self.queries, b[0])

    def hits(self, method: str, k: int, c: float = 0.9, p: float = 0.5) -> DataFrame:
        if method == "ring":
            return self.built(method).search(self.queries, k, c, p)[0]
        return exact.top_k(self.reads(method, k), k)

    def _layout(self, method: str, page: int) -> DataFrame:
        """Page of each vector: by shell, by band and code, by cell (the band with the greatest norms first)."""
        if (method, page) not in self._kept:
            b = self.built(method)
            index, order = {"shell_lsh": (b, ["shell", "vec_id"]), "norm_band_lsh": (b, ["band", "code", "vec_id"]), "residual_pq": (b[-1] if method == "residual_pq" else b, ["cell", "vec_id"])}[method]
            self._kept[method, page] = scratch.written(pages.layout(index.select("vec_id", *order[:-1]), order, pages.row_bytes(self.d), page), "layout")
        return self._kept[method, page]

    def page_counts(self, method: str, read: DataFrame, page: int = pages.PAGE_BYTES) -> DataFrame:
        """qid, pages (of vectors), index_pages.  `read` is what reads() gives, for the ring the stats of its search."""
        b = self.built(method)
        if method == "ring":
            cells = scratch.written(b.final_cells(self.queries, read), "cells")
            return pages.page_access(cells, b.ring.subcells, pages.row_bytes(self.d), page).join(pages.index_pages(cells, b.ring.subcells, b.m, page), "qid")
        data = pages.data_pages(read, self._layout(method, page))
        if method == "shell_lsh":
            return data.join(shell_lsh.table_pages(b, self.queries, read, self.d, self.n, page), "qid")
        if method == "norm_band_lsh":  # codes of all buckets are ranked: (band, code, count) of each
            buckets = b.groupBy("band", "code").count().groupBy().agg(F.ceil(F.count("*") * 16 / page).cast("long").alias("index_pages"))
            return data.crossJoin(F.broadcast(buckets))
        return data.join(residual_pq.code_pages(b[1], self.queries, b[0], page), "qid")

    def figures(self, methods: Iterable[str] = METHODS, ks: Iterable[int] = tuple(range(10, 101, 10)), page: int = pages.PAGE_BYTES, repeat: int = 1) -> DataFrame:
        """Ratio, recall, pages, index_pages, CPU and total seconds of a query by method and k; each k is a search of its own.

        Times are medians of `repeat` searches of the whole batch, divided by its queries."""
        out, nq = None, max(1, self.queries.count())
        for method in methods:
            self.built(method)
            for k in ks:
                times: list[dict] = []
                for _ in range(repeat):
                    times.append({})
                    with metrics.metered(self.spark, times[-1]):
                        if method == "ring":
                            h, read = self.built(method).search(self.queries, k)
                        else:
                            read = scratch.written(self.reads(method, k), "reads")
                            h = exact.top_k(read, k)
                        h = scratch.written(h, "hits")
                mid = {x: sorted(t[x] for t in times)[repeat // 2] / nq for x in ("cpu_seconds", "total_seconds")}
                e = self.exact.where(F.col("rank") <= k)
                both = metrics.overall_ratio(h, e).join(metrics.recall(h, e), "qid").join(self.page_counts(method, read, page), "qid", "left")
                one = tidy(both, self.source, method, "", k, ratio="avg(ratio)", recall="avg(recall)", pages="avg(pages)", index_pages="avg(index_pages)", **{x: f"{v!r}D" for x, v in mid.items()})
                one = scratch.written(one, "figures")
                out = one if out is None else out.unionByName(one)
        return out

    def accuracy(self, methods: Iterable[str] = METHODS, ks: Iterable[int] = (10, 50, 100)) -> DataFrame:
        """Overall ratio and recall by k.  Certificate-driven search runs once for each k."""
        out = None
        for method in methods:
            for k in ks:
                h, e = self.hits(method, k).persist(), self.exact.where(F.col("rank") <= k)
                one = tidy(metrics.overall_ratio(h, e).join(metrics.recall(h, e), "qid"), self.source, method, "", k, ratio="avg(ratio)", recall="avg(recall)")
                out = one if out is None else out.unionByName(one)
        return out

    def pages(self, ks: Iterable[int] = (10, 50, 100), c: float = 0.9, p: float = 0.5) -> DataFrame:
        out = None
        for k in ks:
            e = self.built("ring")
            _, stats = e.search(self.queries, k, c, p)
            one = tidy(e.page_access(self.queries, stats), self.source, "ring", f"c={c},p={p}", k, pages="avg(pages)")
            out = one if out is None else out.unionByName(one)
        return out

    def impact(self, name: str, values: Iterable[float], k: int = 10) -> DataFrame:
        """Ratio, recall, candidates and pages for values of c or p."""
        out = None
        for x in values:
            c, p = (x, 0.5) if name == "c" else (0.9, x)
            e = self.built("ring")
            h, stats = e.search(self.queries, k, c, p)
            ex = self.exact.where(F.col("rank") <= k)
            both = metrics.overall_ratio(h, ex).join(metrics.recall(h, ex), "qid").join(stats, "qid").join(e.page_access(self.queries, stats), "qid", "left")
            one = tidy(both, self.source, "ring", f"{name}={x}", k, ratio="avg(ratio)", recall="avg(recall)", candidates="avg(n_candidates)", pages="avg(pages)")
            out = one if out is None else out.unionByName(one)
        return out

    def sizes(self) -> DataFrame:
        """Bytes of the files that each method keeps beside the vectors (metadata, codebooks and rotations too), and build seconds."""
        rows = []
        for method in METHODS:
            b = self.built(method)
            kept = [f"{self.paths[method]}/{x}" for x in (("sign_cells", "ring/points_narrow", "ring/parts", "ring/subcells", "ring/manifest") if method == "ring" else ("index",))]
            extra = b[0].nbytes if method == "residual_pq" else 0
            size = sum(metrics.index_size(x, self.spark) for x in kept) + extra
            rows += [(self.source, method, "", 0, "index_bytes", float(size)), (self.source, method, "", 0, "build_seconds", self.build_seconds[method])]
        return self.spark.createDataFrame(rows, "source string, method string, param string, k int, measure string, value double")


def param_sweep(points: DataFrame, queries: DataFrame, settings: Iterable[tuple[int, int, int]], radius: float) -> DataFrame:
    """k_p, n_key, k_sp, touched cells and pages for balls of one radius: the answers never change, the costs do."""
    from innersearch.operators import projection, ringindex

    d = points.select(F.size("v")).first()[0]
    m = signcells.best_dimension(points.count())
    w = projection.gaussian_matrix(m, d)
    p = projection.project_points(points, w).persist()
    balls = projection.project_queries(queries, w).select("qid", "qpv", F.lit(-1.0).alias("lo"), F.lit(radius).alias("hi")).persist()
    out = None
    for k_p, n_key, k_sp in settings:
        index = ringindex.build(p, k_p, n_key, k_sp, iters=3)
        cells = ringindex.candidate_cells(index, balls).persist()
        per = pages.page_access(cells, index.subcells, pages.row_bytes(d)).join(cells.groupBy("qid").agg(F.count("*").alias("cells")), "qid")
        one = per.agg(F.avg("cells").alias("cells"), F.avg("pages").alias("pages")).select(F.lit(k_p).alias("k_p"), F.lit(n_key).alias("n_key"), F.lit(k_sp).alias("k_sp"), "cells", "pages")
        out = one if out is None else out.unionByName(one)
    return out


def stepwise_vs_ball(spark: SparkSession, sf_dir: str, source: str = "clustered", k: int = 10) -> DataFrame:
    """method, verified: points compared by the stepwise search and candidates of the ball search."""
    from innersearch.operators import stepwise

    b = Bench(spark, sf_dir, source)
    e = b.built("ring")
    q = e.queries(b.queries)
    pairs = stepwise.pairs_of(e.points, q)
    step = stepwise.stepwise(pairs, e.maxn2, k, e.params.c, e.chi).groupBy("qid").agg(F.first("stop").alias("n")).agg(F.avg("n").alias("verified")).select(F.lit("stepwise").alias("method"), "verified")
    _, stats = e.search(b.queries, k)
    return step.unionByName(stats.agg(F.avg("n_candidates").alias("verified")).select(F.lit("ball").alias("method"), "verified"))
