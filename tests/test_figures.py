"""Experiment frames, certificates by band, the heap aggregate and changes of a written index."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from innersearch.operators import ball, maintenance, projection
from innersearch.plans import catalog, engine, experiments, figures
from innersearch.sources import scratch
from innersearch.sources import vectors as S
from innersearch.streaming import events

from .compare import oracle_rows, rows_of


@pytest.fixture(scope="module")
def bench(spark, sf_dir):
    return experiments.Bench(spark, sf_dir, "clustered", 5)


def test_figures_of_all_methods(bench):
    got = {(r["method"], r["measure"]): r["value"] for r in bench.figures(ks=(10,)).collect()}
    data = -(-bench.n * (8 + 8 * bench.d) // 4096)
    for m in experiments.METHODS:
        assert 0 < got[m, "pages"] <= data and got[m, "index_pages"] >= 1
        assert got[m, "cpu_seconds"] > 0 and got[m, "total_seconds"] > 0
        assert got[m, "ratio"] > 0.9 and 0 <= got[m, "recall"] <= 1


def test_pages_hold_the_points_read(bench):
    """The page count of a baseline is that of its points by brute force in its layout."""
    read = scratch.written(bench.reads("norm_band_lsh", 10), "reads")
    index = bench.built("norm_band_lsh").select("vec_id", "band", "code").orderBy("band", "code", "vec_id").collect()
    page = {r["vec_id"]: i * (8 + 8 * bench.d) // 4096 for i, r in enumerate(index)}
    want = {}
    for r in read.collect():
        want.setdefault(r["qid"], set()).add(page[r["vec_id"]])
    assert {r["qid"]: r["pages"] for r in bench.page_counts("norm_band_lsh", read).collect()} == {k: len(v) for k, v in want.items()}


def test_sizes_are_of_files(bench):
    got = {(r["method"], r["measure"]): r["value"] for r in bench.sizes().collect()}
    assert all(got[m, "index_bytes"] > 0 and got[m, "build_seconds"] > 0 for m in experiments.METHODS)


def test_sizes_need_no_exact_answers(spark, sf_dir):
    b = experiments.Bench(spark, sf_dir, "clustered", 5)
    assert b.sizes().count() == 2 * len(experiments.METHODS) and "exact" not in vars(b)
    assert b.exact.groupBy("qid").count().count() == 5 and b.exact is b.exact


def test_larger_c_or_p_reads_no_less(bench):
    for name, values in (("c", (0.7, 0.9)), ("p", (0.3, 0.9))):
        got = {(r["param"], r["measure"]): r["value"] for r in bench.impact(name, values).collect()}
        low, high = (f"{name}={x}" for x in values)
        for measure in ("candidates", "pages", "ratio"):
            assert got[low, measure] <= got[high, measure] + 1e-9, (name, measure)


def test_banded_search_covers_each_band(spark, sf_dir):
    x, points = figures.banded_setup(spark, sf_dir)
    hits, stats = ball.banded_search(points, x.queries, x.radii, 10, 0.9, catalog.CHI)
    rows = points.select("vec_id", "v", "pv", "n2", "band").collect()
    ids, v, pv, band = (np.array([r[c] for r in rows]) for c in ("vec_id", "v", "pv", "band"))
    n2 = np.array([r["n2"] for r in rows])
    top = {b: n2[band == b].max() for b in set(band.tolist())}
    radius = {r["qid"]: r["radius"] for r in x.radii.collect()}
    got, n = {}, {r["qid"]: r["n_candidates"] for r in stats.collect()}
    for r in hits.orderBy("qid", "rank").collect():
        got.setdefault(r["qid"], []).append(r["vec_id"])
    for r in x.queries.collect():
        ip, pd = v @ np.array(r["qv"]), np.round(np.sqrt(((pv - np.array(r["qpv"])) ** 2).sum(1)), 9)
        seen = (pd <= radius[r["qid"]]) & (ids != r["qid"])
        kth = np.sort(ip[seen])[-10] if seen.sum() >= 10 else None
        for b, m in top.items():
            need = np.inf if kth is None else np.sqrt(catalog.CHI * max(0.0, m + r["qn2"] - 2 * kth / 0.9))
            seen |= (band == b) & (pd <= need) & (ids != r["qid"])
        assert n[r["qid"]] == seen.sum()
        order = np.lexsort((ids[seen], -ip[seen]))[:10]
        assert got[r["qid"]] == ids[seen][order].tolist()
    both = catalog.QUERIES["banded_candidates"](spark, sf_dir).collect()
    assert all(r["banded"] <= r["plain"] for r in both) and sum(r["banded"] for r in both) < sum(r["plain"] for r in both)


def test_topk_heap(spark, sf_dir):
    assert rows_of(catalog.QUERIES["topk_heap"](spark, sf_dir)) == oracle_rows(catalog.SQL["topk_heap"], sf_dir)


def test_changed_index_answers_like_its_live_points(spark, sf_dir, tmp_path):
    raw = S.label_clustered(spark, sf_dir)
    base = raw.where("vec_id % 3 != 0")
    e = engine.build(base, engine.SearchParams(m=3, compensate=False), str(tmp_path / "e"))
    path = str(tmp_path / "e" / "ring")
    far = spark.createDataFrame([(10**6, [50.0] * e.d)], "vec_id long, v array<double>")
    project = lambda p: projection.project_points(p, e.matrix)
    replaced = raw.where("vec_id % 30 = 1").select("vec_id", F.transform("v", lambda z: z * 1.5).alias("v"))
    first = raw.where("vec_id % 3 = 0").unionByName(far).unionByName(replaced)
    assert maintenance.apply_batch(spark, path, 1, project(first), raw.where("vec_id % 30 = 2").select("vec_id"))
    assert not maintenance.apply_batch(spark, path, 1, project(first))  # a replay
    again = raw.where("vec_id % 30 = 2 and vec_id < 60")
    assert maintenance.apply_batch(spark, path, 2, project(again))
    with pytest.raises(ValueError):
        maintenance.apply_batch(spark, path, 0, project(again))

    live = raw.where("vec_id % 30 != 1 and (vec_id % 30 != 2 or vec_id < 60)").unionByName(replaced).unionByName(far)
    now = maintenance.refreshed(e, path)
    want = sorted((r[0], tuple(r[1])) for r in live.collect())
    assert sorted((r["vec_id"], tuple(r["v"])) for r in now.ring.wide.collect()) == want
    assert sorted(r["vec_id"] for r in now.ring.points.collect()) == [i for i, _ in want] and now.n == len(want)
    held = {(r["ikey"], r["sub"]): r["count"] for r in now.ring.points.groupBy("ikey", "sub").count().collect()}
    assert {(r["ikey"], r["sub"]): r["cnt"] for r in now.ring.subcells.collect()} == held
    assert now.maxn2 == pytest.approx(2500.0 * e.d)

    queries = scratch.written(now.queries(S.sample_queries(live, 4)), "queries")
    radii = scratch.written(now.radii(queries).select("qid", "radius"), "radii")
    plain = ball.first_pass(project(live), queries, radii)
    from innersearch.operators import ringindex

    found = ball.first_pass(now.ring.points, queries, radii, fetch=ringindex.fetch(now.ring))
    assert rows_of(found.select("qid", "vec_id")) == rows_of(plain.select("qid", "vec_id"))


def test_stream_of_changes_reaches_the_index(spark, sf_dir, tmp_path):
    raw = S.unit_embeddings(spark, sf_dir)
    e = engine.build(raw.where("vec_id >= 20"), engine.SearchParams(m=3), str(tmp_path / "e"))
    log = raw.where("vec_id < 10").select(F.lit("add").alias("op"), "vec_id", "v", F.lit(1).alias("ts"))
    gone = raw.where("vec_id between 30 and 34 or vec_id = 3").select(F.lit("delete").alias("op"), "vec_id", F.lit(None).cast("array<double>").alias("v"), F.lit(2).alias("ts"))
    log.unionByName(gone).write.parquet(str(tmp_path / "log"))
    stream = spark.readStream.schema("op string, vec_id long, v array<double>, ts int").parquet(str(tmp_path / "log"))
    events.index_changes(stream, str(tmp_path / "e" / "ring"), e.matrix, str(tmp_path / "cp")).awaitTermination()
    ids = {r["vec_id"] for r in maintenance.load(spark, str(tmp_path / "e" / "ring")).points.select("vec_id").collect()}
    all_ = {r["vec_id"] for r in raw.select("vec_id").collect()}
    assert ids == {i for i in all_ if i >= 20 and not 30 <= i <= 34} | ({*range(10)} - {3})
