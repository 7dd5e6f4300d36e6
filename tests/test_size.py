"""Queries on tables larger than the fixtures, or with ids that repeat; copies are made in a folder of the test."""

import os

import pytest
from pyspark.sql import functions as F

from innersearch.plans import catalog

from .compare import TABLES


def copied(spark, sf_dir, to, copies, shift):
    """The tables with `copies` of the embeddings; ids of a copy are `shift` further on."""
    for t in TABLES:
        if t != "embeddings":
            os.symlink(f"{sf_dir}/{t}.parquet", f"{to}/{t}.parquet")
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    e = e.crossJoin(spark.range(copies).withColumnRenamed("id", "i"))
    scale = (F.lit(1.0) - F.col("i") / 100).cast("float")
    e.select((F.col("vec_id") + F.col("i") * shift).alias("vec_id"), F.transform("embedding", lambda x: x * scale).alias("embedding"), "label").write.parquet(f"{to}/embeddings.parquet")
    return str(to)


@pytest.fixture(scope="module")
def larger(spark, sf_dir, tmp_path_factory):
    return copied(spark, sf_dir, tmp_path_factory.mktemp("larger"), 6, 1000)


@pytest.fixture(scope="module")
def repeated(spark, sf_dir, tmp_path_factory):
    return copied(spark, sf_dir, tmp_path_factory.mktemp("repeated"), 3, 0)


def same(spark, name, sf_dir):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        at = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at + '/*.parquet' if os.path.isdir(at) else at}'")
    cur = con.execute(catalog.SQL[name])
    names = [c[0] for c in cur.description]
    got = [tuple(r[n] for n in names) for r in catalog.QUERIES[name](spark, sf_dir).collect()]
    assert sorted(got, key=repr) == sorted(cur.fetchall(), key=repr)


def test_lateral_topk_of_repeated_ids(spark, repeated):
    same(spark, "lateral_topk", repeated)


def test_norm_band_topk_reads_what_its_sql_reads(spark, larger):
    same(spark, "norm_band_topk", larger)


def test_residual_pq_sends_no_name_of_this_package(spark, sf_dir):
    """Executors may not have the package: what is sent to them loads without it."""
    import pickle
    import subprocess
    import sys

    from pyspark import cloudpickle

    from innersearch.operators.baselines import residual_pq
    from innersearch.sources import vectors as S

    book = residual_pq.train(S.unit_embeddings(spark, sf_dir), 64, cells=4)
    sent = pickle.dumps((pickle.dumps(vars(book)), cloudpickle.dumps(residual_pq._encode)))
    load = "import pickle, sys; a, b = pickle.loads(sys.stdin.buffer.read()); import numpy; pickle.loads(b)(pickle.loads(a), numpy.ones((3, 64)))"
    subprocess.run([sys.executable, "-c", load], input=sent, check=True, cwd="/")


def test_rotations_of_a_large_cell_are_small(spark, sf_dir, monkeypatch):
    """The left factor of a decomposition of 20,000 rows would take 3.2 GB."""
    import tracemalloc

    from innersearch.operators.baselines import residual_pq

    x = spark.range(20_000).select(F.col("id").alias("vec_id"), F.array(*[F.sin(F.col("id") * (j + 1.7)) for j in range(4)]).alias("v"))
    tracemalloc.start()
    book = residual_pq.train(x, 4, subspaces=5, centroids=4, cells=1)
    assert tracemalloc.get_traced_memory()[1] < 2**28
    tracemalloc.stop()
    turned = book.rotations[0].T @ book.rotations[0]
    assert abs(turned - residual_pq.np.eye(5)).max() < 1e-9


def test_residual_pq_short_list_by_brute_force(spark, larger):
    """Points read are those of the least table distances, ties to the smaller id."""
    import numpy as np

    from innersearch.operators.baselines import residual_pq
    from innersearch.sources import vectors as S

    p = S.skewed_embeddings(spark, larger)
    book = residual_pq.train(p, 64, cells=8)
    queries = p.where("vec_id % 1000 = 7 and vec_id < 3000").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    got = {}
    for r in residual_pq.reads(residual_pq.encode(p, book), queries, book, 3, 40).collect():
        got.setdefault(r["qid"], set()).add(r["vec_id"])
    rows = p.orderBy("vec_id").collect()
    ids, v = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    cell, codes = book.encode(v)
    for qid in (7, 1007, 2007):
        q = v[ids == qid][0]
        x = np.concatenate([q * np.sqrt(book.bound2) / np.linalg.norm(q), np.zeros(1 + book.pad)])
        near = np.full(len(ids), np.inf)
        for c in np.argsort(((book.cells - x) ** 2).sum(1), kind="stable")[:3]:
            r = (x - book.cells[c]) @ book.rotations[c]
            w = len(r) // len(book.books)
            at = cell == c
            near[at] = sum(((b[codes[at, i]] - r[i * w : (i + 1) * w]) ** 2).sum(1) for i, b in enumerate(book.books))
        near[ids == qid] = np.inf
        assert got[qid] == set(ids[np.lexsort((ids, np.round(near, 12)))[:40]].tolist())


def test_latent_factors_by_numpy(spark, sf_dir, monkeypatch):
    """The same factors whatever fits a block, a slice or a piece; nothing of the size of the parts is a Python list."""
    import numpy as np

    from innersearch.sources import vectors as S

    o, li = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("orders", "lineitem"))
    cells = li.join(o, li.l_orderkey == o.o_orderkey).groupBy("o_custkey", "l_partkey").agg(F.sum("l_quantity").alias("x")).collect()
    parts = sorted(r[0] for r in spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey").collect())
    custs = sorted({r[0] for r in cells})
    a = np.zeros((len(custs), len(parts)))
    for c, p, x in cells:
        a[custs.index(c), parts.index(p)] = x
    block = np.linalg.qr(np.random.default_rng(7).standard_normal((len(parts), 16)))[0]
    for _ in range(4):
        block = np.linalg.qr(a.T @ (a @ block))[0]
    squares, basis = np.linalg.eigh(block.T @ (a.T @ (a @ block)))
    want = a @ (block @ basis) @ (block @ basis).T
    for sizes in ((2**26, 65_536, 131_072), (8 * len(parts) * 5, 50, 37)):
        for name, size in zip(("BLOCK_BYTES", "QR_ROWS", "PIECE"), sizes, strict=True):
            monkeypatch.setattr(S, name, size)
        monkeypatch.setattr(S.orthogonal, "__defaults__", (sizes[1],))
        items, users = S.latent_factors(spark, sf_dir)
        items, users = ({r[0]: r[1] for r in x.collect()} for x in (items, users))
        assert sorted(items) == parts and sorted(users) == custs
        got = np.array([users[c] for c in custs]) @ np.array([items[p] for p in parts]).T
        assert abs(got - want).max() < 1e-6


@pytest.mark.parametrize("name", ["cost_model", "selectivity", "sign_neighbors", "toy_points"])
def test_results_come_from_the_table(spark, sf_dir, larger, name):
    """The SQL's rows on two tables; with points taken away the rows change."""
    same(spark, name, sf_dir)
    same(spark, name, larger)
    few = os.path.join(larger, "..", f"few_{name}")
    os.makedirs(few, exist_ok=True)
    spark.read.parquet(f"{sf_dir}/embeddings.parquet").where("vec_id < 2").write.mode("overwrite").parquet(f"{few}/embeddings.parquet")
    assert sorted(catalog.QUERIES[name](spark, few).collect()) != sorted(catalog.QUERIES[name](spark, sf_dir).collect())


def test_blocked_search_of_many_batches(spark, larger):
    """Batches pass on what reaches the k-th best so far: no answer is lost, ties stay."""
    from innersearch.operators import exact
    from innersearch.sources import vectors as S

    p = S.unit_embeddings(spark, larger)
    p = p.unionByName(p.where("vec_id < 500").selectExpr("vec_id + 100000 as vec_id", "v"))  # copies tie
    queries = S.sample_queries(p, 12)
    want = exact.exact_topk(p, queries, 7).collect()
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "64")
    try:
        got = exact.exact_topk_blocked(p, queries, 7).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    key = lambda rows: sorted((r["qid"], r["rank"], round(r["ip"], 9)) for r in rows)
    assert key(got) == key(want) and len(got) == 84


def test_shell_pairs_are_a_byte_each(spark, sf_dir):
    """Levels of all pairs take a byte, not a row; the best of a shell give the answers that all points read give."""
    from innersearch.operators.baselines import shell_lsh
    from innersearch.operators.exact import top_k
    from innersearch.sources import vectors as S

    p = S.skewed_embeddings(spark, sf_dir)
    index = shell_lsh.build(p, 64)
    queries = p.where("vec_id % 50 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))
    n = p.count()
    leveled, asked = shell_lsh.levels(index, queries, 64, n)
    assert leveled.count() == n and {len(r[0]) for r in leveled.select("levels").collect()} == {len(asked)}
    key = lambda df: sorted((r["qid"], r["rank"], r["vec_id"], r["ip"]) for r in df.collect())
    assert key(shell_lsh.search(index, queries, 64, n)) == key(top_k(shell_lsh.reads(index, queries, 64, n), 10))


def test_products_come_in_slices(spark, monkeypatch):
    """The driver holds one slice of a product, within BLOCK_BYTES; the slices make up the whole of it."""
    import numpy as np

    from innersearch.sources import vectors as S

    a = np.random.default_rng(1).random((9, 30)) * (np.random.default_rng(2).random((9, 30)) < 0.4)
    rows = spark.createDataFrame([(i, np.nonzero(x)[0].tolist(), x[x > 0].tolist()) for i, x in enumerate(a)], "cust long, at array<long>, x array<double>")
    block = np.random.default_rng(3).random((30, 8))
    monkeypatch.setattr(S, "BLOCK_BYTES", 8 * 30 * 3)
    monkeypatch.setattr(S, "PIECE", 7)
    got = list(S._gram(rows, block, 30))
    assert [lo for lo, _ in got] == [0, 3, 6] and all(x.nbytes <= 8 * 30 * 3 for _, x in got)
    assert abs(np.hstack([x for _, x in got]) - a.T @ (a @ block)).max() < 1e-9


def test_lines_of_unknown_parts(spark, sf_dir, tmp_path):
    """Lines of parts that the part table lacks are left out, with the customers who have no others."""
    from innersearch.sources import vectors as S

    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    part, o = read("part").where("p_partkey % 3 != 0"), read("orders").where("o_custkey < 40")
    part.write.parquet(f"{tmp_path}/part.parquet")
    o.write.parquet(f"{tmp_path}/orders.parquet")
    li = read("lineitem").withColumn("l_partkey", F.when(F.col("l_orderkey").isin([r[0] for r in o.where("o_custkey < 10").select("o_orderkey").collect()]), F.lit(0)).otherwise(F.col("l_partkey")))
    li.write.parquet(f"{tmp_path}/lineitem.parquet")
    known = li.join(o, li.l_orderkey == o.o_orderkey).join(part, li.l_partkey == part.p_partkey)
    items, users = S.latent_factors(spark, str(tmp_path))
    assert sorted(r[0] for r in users.select("vec_id").collect()) == sorted(r[0] for r in known.select("o_custkey").distinct().collect())
    assert items.count() == part.count()


def test_products_take_the_place_of_their_columns(spark, monkeypatch):
    """Pieces of a product are put where its columns were while others are still to be sent; the driver holds no more of it."""
    import numpy as np

    from innersearch.sources import vectors as S

    a = np.random.default_rng(1).random((9, 30)) * (np.random.default_rng(2).random((9, 30)) < 0.4)
    rows = spark.createDataFrame([(i, np.nonzero(x)[0].tolist(), x[x > 0].tolist()) for i, x in enumerate(a)], "cust long, at array<long>, x array<double>")
    block = np.asfortranarray(np.random.default_rng(3).random((30, 8)))
    want = a.T @ (a @ block)
    monkeypatch.setattr(S, "BLOCK_BYTES", 8 * 30 * 3)
    monkeypatch.setattr(S, "PIECE", 7)
    seen = []
    for lo, at, x in S._pieces(rows, block, 30):
        seen.append((lo, at))
        assert x.nbytes <= 8 * 7 * 3
        block[at : at + len(x), lo : lo + x.shape[1]] = x
    assert sorted(seen) == [(lo, at) for lo in (0, 3, 6) for at in range(0, 30, 7)]
    assert abs(block - want).max() < 1e-9


def test_codebooks_are_trained_by_slices(spark):
    """All distances of 20,000 points from 256 centroids would take 41 MB, and twice that with their parts."""
    import tracemalloc

    from innersearch.operators.baselines import residual_pq

    x = spark.range(20_000).select(F.col("id").alias("vec_id"), F.array(*[F.sin(F.col("id") * (j + 1.7)) for j in range(4)]).alias("v"))
    tracemalloc.start()
    book = residual_pq.train(x, 4, subspaces=5, centroids=256, cells=4)
    assert tracemalloc.get_traced_memory()[1] < 2**25
    tracemalloc.stop()
    v = residual_pq.np.array([r[0] for r in x.orderBy("vec_id").select("v").collect()])
    cell, codes = book.encode(v)
    lifted = book.lift(v)
    assert (cell == ((lifted[:, None] - book.cells[None]) ** 2).sum(2).argmin(1)).mean() > 0.9999
    r = book.rotated(lifted, cell)
    assert (codes[:, 0] == ((r[:, :1] - book.books[0].T) ** 2).argmin(1)).mean() > 0.99


def test_recommendations_for_every_customer(spark, sf_dir):
    """The five greatest products of every customer who has factors, by brute force."""
    import numpy as np

    from innersearch.sources import vectors as S

    items, users = ({r[0]: r[1] for r in x.collect()} for x in S.latent_factors(spark, sf_dir))
    buyers = {r[0] for r in spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_custkey").distinct().collect()}
    got = {}
    for r in sorted(catalog.QUERIES["recommend_for_customer"](spark, sf_dir).collect(), key=lambda r: (r["qid"], r["rank"])):
        got.setdefault(r["qid"], []).append(r["ip"])
    assert got.keys() == users.keys() == buyers
    ip = np.array([users[u] for u in sorted(users)]) @ np.array([items[i] for i in sorted(items)]).T
    want = -np.sort(-ip, axis=1)[:, :5]
    assert abs(np.array([got[u] for u in sorted(users)]) - want).max() < 1e-6


@pytest.mark.parametrize("sizes", [(2**26, 1024, 4096), (40 * 64 * 9, 16, 7)])
def test_search_of_many_queries_by_brute_force(spark, monkeypatch, sizes):
    """Slices, tiles and steps lose no answer; ties go to the smaller id, also for a query of zeros."""
    import numpy as np

    from innersearch.operators import exact

    for name, size in zip(("SLICE_BYTES", "TILE_ROWS", "STEP_ROWS"), sizes, strict=True):
        monkeypatch.setattr(exact, name, size)
    r = np.random.default_rng(5)
    v = r.integers(-3, 4, (900, 6)) * r.choice([0.25, 1.0, 8.0], (900, 1))
    v[300:600] = v[:300]  # copies tie
    v[::50] = 0
    q = r.integers(-3, 4, (60, 6)).astype(float)
    q[7] = 0
    points = spark.createDataFrame([(7 * i % 900, [float(y) for y in x]) for i, x in enumerate(v)], "vec_id long, v array<double>")
    queries = spark.createDataFrame([(i, [float(y) for y in x]) for i, x in enumerate(q)], "qid long, qv array<double>")
    ids = np.array([7 * i % 900 for i in range(900)])
    got = {(x["qid"], x["rank"]): (x["vec_id"], x["ip"]) for x in exact.exact_topk_many(points, queries, 8).collect()}
    want = {(i, n + 1): (int(ids[j]), float(v[j] @ x)) for i, x in enumerate(q) for n, j in enumerate(np.lexsort((ids, -(v @ x)))[:8])}
    assert got == want
    few = exact.exact_topk_many(points.where("vec_id < 3"), queries, 8).collect()
    assert len(few) == 180 and exact.exact_topk_many(points.where("vec_id < 0"), queries, 8).count() == 0
