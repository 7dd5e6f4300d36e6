import pytest
from pyspark.sql import functions as F

from innersearch.functions import chisq
from innersearch.functions import vectors as V
from innersearch.operators import ball, exact, kmeans, metrics, projection, ringindex, signcells, stepwise
from innersearch.plans import catalog, engine
from innersearch.sources import vectors as S

from .compare import oracle_rows, rows_of

QUICK = (
    "exact_topk", "exact_topk_blocked", "project_points", "certificate_a", "certificate_b", "nearest_euclid", "stream_search", "stepwise_k1", "stepwise_topk", "radius_probe", "best_dimension",
    "ball_topk", "ball_stats", "plain_keys", "page_access", "lift_nn_topk", "shell_partition", "norm_band_topk", "overall_ratio", "recall_by_k",
    "asof_event_query", "range_frame_density", "win_session", "win_sliding", "interval_join_events", "except_hits", "cube_ratio",
)


@pytest.mark.parametrize("name", QUICK)
def test_oracle(spark, sf_dir, name):
    assert rows_of(catalog.QUERIES[name](spark, sf_dir)) == oracle_rows(catalog.SQL[name], sf_dir)


def toy(spark, qv):
    points = projection.project_points(S.toy_points(spark), S.TOY_MATRIX)
    queries = projection.project_queries(spark.createDataFrame([(100, list(qv))], "qid long, qv array<double>"), S.TOY_MATRIX)
    return points, queries


@pytest.mark.parametrize(
    "qv, p, anchor, passed, best, reason",
    [
        ((3.0, 4.0), 0.5, 0, True, 2, "A"),
        ((3.0, 4.0), 0.05, 3, True, 2, "A"),
        ((0.6, 0.8), 0.3, 0, True, 1, "extended"),
        ((0.6, 0.8), 0.5, 0, True, 1, "extended"),
        ((0.6, 0.8), 0.9, 0, False, 2, "extended"),
    ],
)
def test_worked_example(spark, qv, p, anchor, passed, best, reason):
    points, queries = toy(spark, qv)
    chi = chisq.quantile(2, p)
    radii = signcells.radius_probe(signcells.build_cells(points, 2), queries, 2, 0.9, chi)
    r = radii.first()
    assert r["anchor_id"] == anchor
    assert r["test_passed"] == passed
    hits, stats = ball.ball_search(points, queries, radii.select("qid", "radius"), 25.0, 1, 0.9, chi)
    assert hits.first()["vec_id"] == best
    assert stats.first()["stop_reason"] == reason


def test_stepwise_worked_example(spark):
    points, queries = toy(spark, (0.6, 0.8))
    pairs = stepwise.pairs_of(points, queries)
    for p, stop, best, reason in ((0.3, 3, 1, "B"), (0.5, 5, 2, "B"), (0.9, 5, 2, "exhausted")):
        r = stepwise.stepwise_k1(pairs, 25.0, 0.9, chisq.quantile(2, p)).first()
        assert (r["stop"], r["vec_id"], r["reason"]) == (stop, best, reason)


def test_bounds_hold(spark, sf_dir):
    x = catalog.Setup(spark, sf_dir)
    both = x.points.withColumn("code", signcells.sign_code("pv", 4)).crossJoin(F.broadcast(x.queries.withColumn("qcode", signcells.sign_code("qpv", 4))))
    low1 = signcells.sign_lower_bound(F.col("code"), F.col("qcode"), F.col("qpv"), 4)
    low2 = signcells.sign_lower_bound(F.col("code"), F.col("qcode"), F.col("qpv"), 4, "l2")
    true, up2, up1 = V.dist("v", "qv"), F.sqrt("n2") + F.sqrt("qn2"), F.col("n1") + F.col("qn1")
    bad = both.select(low1.alias("a"), low2.alias("b"), V.dist("pv", "qpv").alias("d"), true.alias("t"), up2.alias("u"), up1.alias("w"))
    assert bad.where("a > b + 1e-8 or b > d + 1e-8 or t > u + 1e-8 or u > w + 1e-8").count() == 0


def test_index_never_changes_answers(spark, sf_dir):
    x = catalog.Setup(spark, sf_dir, "clustered")
    want = rows_of(x.first.select("qid", "vec_id"))
    index = ringindex.build(x.points, 4, 3, 2)
    assert rows_of(ball.first_pass(index.points, x.queries, x.radii, fetch=ringindex.fetch(index)).select("qid", "vec_id")) == want
    assert index.subcells.agg(F.sum("cnt")).first()[0] == x.points.count()
    assert index.points.where(F.col("ikey") < F.col("part") * index.factor).count() == 0


def test_max_norm_certificate_is_sound(spark, sf_dir):
    x = catalog.Setup(spark, sf_dir, "clustered")
    found = stepwise.stepwise_k1(x.pairs, x.maxn2, 0.7, chisq.quantile(4, 0.99), "A").where("reason = 'A'")
    best = x.exact.where("rank = 1").select("qid", F.col("ip").alias("top"))
    assert found.join(best, "qid").where("ip < 0.7 * top - 1e-9").count() == 0


def test_guarantee_rate(spark, sf_dir):
    raw = S.label_clustered(spark, sf_dir).persist()
    queries = S.sample_queries(raw, 40)
    truth = exact.exact_topk_blocked(raw, queries, 1).persist()
    rates = []
    for seed in (1, 2, 3):
        e = engine.build(raw, engine.SearchParams(k=1, m=3, seed=seed, use_index=False))
        rates.append(metrics.guarantee_rate(e.search(queries)[0], truth, 0.9).first()[0])
    assert sum(rates) / 3 >= 0.5


def test_lloyd_inertia_falls(spark, sf_dir):
    x = catalog.Setup(spark, sf_dir, "clustered")
    _, inertia = kmeans.lloyd(x.points, "pv", 4, 5)
    assert all(a >= b - 1e-6 for a, b in zip(inertia, inertia[1:], strict=False))


def test_chi_square_ratio(spark, sf_dir):
    p = S.unit_embeddings(spark, sf_dir).where("vec_id < 20")
    pairs = p.where("vec_id < 10").crossJoin(p.where("vec_id >= 10").withColumnRenamed("vec_id", "o").withColumnRenamed("v", "b")).select(F.concat_ws("-", "vec_id", "o").alias("id"), F.col("v").alias("a"), "b")
    r = projection.ratio_sample(pairs, 4, 64, range(12)).agg(F.avg("ratio"), F.var_samp("ratio")).first()
    assert 3.2 < r[0] < 4.8 and 4 < r[1] < 13


def test_edges(spark):
    pts = projection.project_points(spark.createDataFrame([(1, [0.0, 0.0]), (2, [1.0, 1.0]), (3, [1.0, 1.0])], "vec_id long, v array<double>"), S.TOY_MATRIX)
    qs = projection.project_queries(spark.createDataFrame([(9, [0.0, 0.0]), (8, [-1.0, -1.0])], "qid long, qv array<double>"), S.TOY_MATRIX)
    radii = signcells.radius_probe(signcells.build_cells(pts, 2), qs, 2, 0.9, 1.0)
    hits, stats = ball.ball_search(pts, qs, radii.select("qid", "radius"), 2.0, 10, 0.9, 1.0)
    assert hits.groupBy("qid").count().where("count = 3").count() == 2  # k > n: all points, and no certificate
    assert {r["stop_reason"] for r in stats.collect()} == {"exhausted"}
