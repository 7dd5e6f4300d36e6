"""Queries over all rows against brute force in numpy."""

import numpy as np
import pytest

from innersearch.plans import catalog, whole


@pytest.fixture(scope="module")
def table(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding").orderBy("vec_id").collect()
    return np.array([r[0] for r in rows]), np.array([r[1] for r in rows], np.float64)


def run(spark, sf_dir, name):
    return [tuple(r) for r in catalog.QUERIES[name](spark, sf_dir).collect()]


def test_heavy_pairs_all(spark, sf_dir, table, monkeypatch):
    ids, v = table
    ip = np.round(v @ v.T, 9)
    want = {(int(ids[i]), int(ids[j])) for i, j in zip(*np.nonzero(ip > 0.3), strict=True) if ids[i] < ids[j]}
    points = whole.S.unit_embeddings(spark, sf_dir)
    for size in (whole.PAIR_BLOCK, 90):
        got = [tuple(r) for r in whole.pairs_above(points, 0.3, size).collect()]
        assert len(got) == len(want) and set(got) == want
    assert max(b for _, b in want) >= 200


@pytest.mark.parametrize("block", [512, 4])
@pytest.mark.parametrize("name", ["pair_dots_all", "sql_functions_all", "posexplode_dots_all", "distance_identity_all"])
def test_all_pairs(spark, sf_dir, table, monkeypatch, name, block):
    monkeypatch.setattr(whole, "QUERY_BLOCK", block)
    ids, v = table
    got = {(a, b): x for a, b, x in run(spark, sf_dir, name)}
    want = {(int(a), int(b)): (((v[j] - v[i]) ** 2).sum() if name.startswith("distance") else v[i] @ v[j]) for i, a in enumerate(ids) if a % 50 == 0 for j, b in enumerate(ids) if a != b}
    assert got.keys() == want.keys() and all(abs(got[x] - want[x]) < 2e-5 for x in want)


def test_certificate_b_all(spark, sf_dir, table):
    ids, v = table
    w = np.array(whole.MATRIX)
    p, top = v @ w.T, (v * v).sum(1).max()
    got = run(spark, sf_dir, "certificate_b_all")
    assert len(got) == sum(ids % 50 == 0) * (len(ids) - 1)
    at = {int(x): i for i, x in enumerate(ids)}
    for qid, vec_id, holds in got:
        i, j = at[qid], at[vec_id]
        margin = top + v[i] @ v[i] - 2 * (v[i] @ v[j]) / whole.C
        gap = ((p[i] - p[j]) ** 2).sum() - whole.CHI * margin
        if abs(gap) > 1e-6 and abs(margin) > 1e-6:
            assert holds == (margin > 0 and gap >= 0)


def test_page_access_all_covers_the_balls(spark, sf_dir):
    """Each query reads at least the pages of the points in its ball, and at most all pages."""

    got = dict(run(spark, sf_dir, "page_access_all"))
    x = catalog.Setup(spark, sf_dir)
    x.queries = catalog.projection.project_queries(whole.query_set(x.raw), whole.MATRIX)
    size = catalog.pages.row_bytes(64)
    cell = x.plain.points.join(x.plain.subcells.select("ikey", "sub", "row_offset", "cnt"), ["ikey", "sub"])
    inside = x.first.select("qid", "vec_id").join(cell, "vec_id").select("qid", "row_offset", "cnt").distinct()
    want = {}
    for qid, offset, cnt in inside.collect():
        want.setdefault(qid, set()).update(range(offset * size // 4096, ((offset + cnt) * size - 1) // 4096 + 1))
    everything = -(-x.raw.count() * size // 4096)
    assert want.keys() <= got.keys() and all(len(want[i]) <= got[i] <= everything for i in want)


def test_stream_search_takes_all_events(spark, sf_dir):
    users = {r[0] for r in spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id").distinct().collect()}
    n = spark.read.parquet(f"{sf_dir}/embeddings.parquet").count()
    assert {r[0] for r in run(spark, sf_dir, "stream_search")} == {u % n for u in users}
    big = "/root/testdata/sf0.01"
    users = {r[0] for r in spark.read.parquet(f"{big}/events.parquet").select("user_id").distinct().collect()}
    assert {r[0] for r in run(spark, big, "stream_search")} == {u % 500 for u in users}


def test_searches_ask_every_fiftieth_row(spark, sf_dir, table, monkeypatch):
    monkeypatch.setattr(whole, "QUERY_BLOCK", 4)
    ids, v = table
    due = {int(i) for i in ids if i % 50 == 0}
    got = {}
    for qid, rank, vec_id, _ in sorted(run(spark, sf_dir, "exact_topk_all")):
        got.setdefault(qid, []).append(vec_id)
    ip = v @ v.T
    np.fill_diagonal(ip, -np.inf)
    assert got == {q: [int(x) for x in ids[np.lexsort((ids, -ip[q]))[:10]]] for q in due}
    for name in ("ball_topk_all", "residual_pq_search", "power_lsh_search"):
        assert {r["qid"] for r in catalog.QUERIES[name](spark, sf_dir).select("qid").distinct().collect()} == due
    users = {r[0] for r in spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_custkey").distinct().collect()}
    assert {r["qid"] for r in catalog.QUERIES["recommend_for_customer"](spark, sf_dir).select("qid").distinct().collect()} == {u for u in users if u % 50 == 0}


def test_shell_hashes_follow_the_number_of_points(spark, sf_dir):
    points = whole.S.skewed_embeddings(spark, sf_dir)
    n = points.count()
    want = catalog.shell_lsh.params(n)["functions"]
    index = catalog.shell_lsh.build(points, 64)
    assert want != 32 and {r[0] for r in index.selectExpr("size(h)").distinct().collect()} == {want}
    queries = whole.query_set(points)
    assert {r[0] for r in catalog.shell_lsh.search(index, queries, 64, n).select("qid").distinct().collect()} == {r[0] for r in queries.select("qid").collect()}
