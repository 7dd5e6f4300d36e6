"""The index on files, ranks without a global window, and samples at small rates."""

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from innersearch.operators import ball, exact, kmeans, ringindex
from innersearch.plans import catalog, engine
from innersearch.sources import scratch
from innersearch.sources import vectors as S

from .compare import oracle_rows, rows_of


@pytest.mark.parametrize("name", ["flagship_search", "ring_lookup", "norm_bands", "page_layouts", "norm_band_topk"])
def test_oracle(spark, sf_dir, name):
    assert rows_of(catalog.QUERIES[name](spark, sf_dir)) == oracle_rows(catalog.SQL[name], sf_dir)


def test_search_does_not_shuffle_points(spark, sf_dir):
    e = engine.build(S.label_clustered(spark, sf_dir), engine.SearchParams(m=4))
    q = scratch.written(e.queries(S.sample_queries(S.label_clustered(spark, sf_dir), 5)), "queries")
    found = ball.first_pass(e.ring.points, q, scratch.written(e.radii(q).select("qid", "radius"), "radii"), fetch=ringindex.fetch(e.ring))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan and "Exchange hashpartitioning" not in plan
    assert not spark.catalog.listTables() and "InMemoryTableScan" not in plan


def test_enclosing_radius_holds_k(spark, sf_dir):
    x = catalog.Setup(spark, sf_dir, "clustered")
    index = ringindex.build(x.points, 4, 3, 2)
    reach = lambda q: ringindex.enclosing(index, q, 10)
    want = rows_of(ball.kth_near(x.points, x.queries, 10))
    assert rows_of(ball.kth_near(index.points, x.queries, 10, fetch=ringindex.fetch(index), enclosing=reach)) == want
    assert ringindex.enclosing(index, x.queries, 10**6).where("reach is not null").count() == 0


def test_cells_are_bounded():
    for n in (10, 10**4, 10**9, 10**13):
        k_p, n_key, k_sp = ringindex.params_for(n, 64)
        assert 1 <= k_p * n_key * k_sp <= ringindex.MAX_CELLS


def test_ranked_equals_a_window(spark):
    df = spark.range(1000).selectExpr("id AS vec_id", "cast(id % 7 AS double) AS n2").repartition(5)
    got, n = exact.ranked(df, [F.desc("n2"), F.col("vec_id")])
    want = df.withColumn("place", (F.row_number().over(Window.orderBy(F.desc("n2"), "vec_id")) - 1).cast("long"))
    assert n == 1000 and rows_of(got.select("vec_id", "place")) == rows_of(want.select("vec_id", "place"))


def test_samples_at_small_rates(spark):
    """A rate far below a millionth still draws its share."""
    got = spark.range(10**6).where(kmeans.hash_share("id") < 1e-4).count()
    assert 50 < got < 160
    assert spark.range(1).select(kmeans.hash_share("id").alias("x")).where("x >= 0 and x < 1").count() == 1


def test_fetch_by_batches_equals_the_joins(spark, sf_dir, monkeypatch):
    """Points of balls come the same by batches and by joins, also when a task makes few pairs at once; a point left is one row."""
    e = engine.build(S.skewed_embeddings(spark, sf_dir), engine.SearchParams(m=4))
    q = scratch.written(e.queries(S.sample_queries(S.skewed_embeddings(spark, sf_dir), 9)), "queries")
    radii = scratch.written(e.radii(q).select("qid", "radius"), "radii")
    balls = scratch.written(q.join(radii, "qid").select("qid", "qv", "qpv", F.lit(0.5).alias("lo"), F.col("radius").alias("hi")), "balls")
    seen, keep = {}, scratch.written
    monkeypatch.setattr(scratch, "written", lambda df, name: seen.setdefault(name, keep(df, name)) if name == "in_ball" else keep(df, name))
    got = sorted(ringindex.fetch(e.ring)(e.ring.points, balls).collect())
    left = seen["in_ball"]
    assert left.select("vec_id").distinct().count() == left.count() < len(got)
    monkeypatch.setattr(scratch, "written", keep)
    monkeypatch.setattr(ringindex, "PAIRS", 10)
    assert sorted(ringindex.fetch(e.ring)(e.ring.points, balls).collect()) == got
    want = sorted(ringindex._fetch_joined(e.ring, e.ring.points, balls, ringindex.candidate_cells(e.ring, balls), True).collect())
    assert got == want


def test_table_pages_by_brute_force(spark, sf_dir):
    """Entries within reach in each hash table, a page more than they fill, and hashes to the last bit."""
    from innersearch.operators import projection
    from innersearch.operators.baselines import shell_lsh

    p = S.skewed_embeddings(spark, sf_dir)
    n = p.count()
    index = scratch.written(shell_lsh.build(p, 64), "shells")
    lifted = index.withColumn("u", shell_lsh.transforms.lift_point(F.col("v"), F.col("bound") * F.col("bound")))
    by = shell_lsh.params(n)
    assert lifted.where(shell_lsh.projected("u", projection.gaussian_matrix(by["functions"], 65)) != F.col("h")).count() == 0
    queries = S.sample_queries(p, 5)
    read = scratch.written(shell_lsh.reads(index, queries, 64, n, 5), "reads")
    got = dict(shell_lsh.table_pages(index, queries, read, 64, n, 64).collect())
    hashes = {r["qid"]: r["qh"] for r in shell_lsh.hashed(queries, 64, by["functions"]).collect()}
    rows, want = index.collect(), {}
    for qid, shell, last in read.select("qid", "shell", "last").distinct().collect():
        mine = [r for r in rows if r["shell"] == shell]
        for f in range(by["functions"]):
            inside = sum(abs(r["h"][f] - hashes[qid][f] * r["bound"]) <= by["w"] * (r["bound"] / 50) * 2.0**last / 2 for r in mine)
            want[qid] = want.get(qid, 0) + inside // 4 + 1
    assert got == want
