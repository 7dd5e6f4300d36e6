"""Vector sources on the given tables.  Points are (vec_id long, v array<double>), queries (qid, qv)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.sources import scratch

#: The five points of the worked example, and its projection (twice the identity).
TOY = ((0, (-0.1, -0.2)), (1, (2.0, 1.0)), (2, (4.0, 3.0)), (3, (-1.0, 2.0)), (4, (2.0, -1.0)))
TOY_MATRIX = ((2.0, 0.0), (0.0, 2.0))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unit_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select("vec_id", V.as_double("embedding").alias("v"))


def norm_scale(spread: float) -> Column:
    """A deterministic spread of norms: 1 / (1 + (id * 7919 mod 97) / spread)."""
    return F.lit(1.0) / (1 + ((F.col("vec_id") * 7919) % 97) / F.lit(spread))


def skewed_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = norm_scale(16.0)
    return unit_embeddings(spark, sf_dir).select("vec_id", V.scale("v", s).alias("v"))


def label_clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points around the first vector of their label, with mildly different norms."""
    e = read(spark, sf_dir, "embeddings").select("vec_id", "label", V.as_double("embedding").alias("v"))
    centre = e.groupBy("label").agg(F.min_by("v", "vec_id").alias("centre"))
    s = norm_scale(48.0)
    moved = F.zip_with("centre", "v", lambda c, x: c + 0.35 * x)
    return e.join(F.broadcast(centre), "label").select("vec_id", V.scale(moved, s).alias("v"))


def term_vectors(spark: SparkSession, sf_dir: str, dim: int = 64) -> DataFrame:
    """Hashed word counts of documents: coordinate = first 28 bits of md5(word) mod dim."""
    words = read(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w != ''")
    at = (F.conv(F.substring(F.md5("w"), 1, 7), 16, 10).cast("long") % dim).cast("int")
    counts = words.select("doc_id", at.alias("j")).groupBy("doc_id", "j").count()
    sparse = counts.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("j", F.col("count").cast("double")))).alias("m"))
    return sparse.select(F.col("doc_id").alias("vec_id"), F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: F.coalesce(F.try_element_at("m", j), F.lit(0.0))).alias("v"))


def lineitem_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six scaled features of each lineitem; the id packs its keys and a row number for equal keys."""
    li = read(spark, sf_dir, "lineitem")
    month = F.month("l_shipdate") * F.lit(0.5235987755982988)
    v = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 1e5, F.col("l_discount") * 10, F.col("l_tax") * 10, F.sin(month), F.cos(month))
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    rn = F.row_number().over(Window.partitionBy(*keys).orderBy("l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_shipdate")) - 1
    packed = (((F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 262144 + F.col("l_partkey")) * 16384 + F.col("l_suppkey")) * 4 + rn
    return li.select(packed.cast("long").alias("vec_id"), v.alias("v"))


#: Most bytes of a part-by-rank block that are sent to the tasks at once; more columns take more passes.
BLOCK_BYTES = 2**26
#: Rows of a block that are orthogonalized at once, and parts of a piece of a product that the driver receives.
QR_ROWS, PIECE = 65_536, 131_072


def orthogonal(block, rows: int = QR_ROWS):
    """An orthonormal basis of a tall block's columns, in its own memory: factors of slices, then of their triangles."""
    import numpy as np

    width = block.shape[1]
    cuts = [(a, min(a + rows, len(block))) for a in range(0, len(block), rows)]
    if len(cuts) > 1 and cuts[-1][1] - cuts[-1][0] < width:  # a slice has at least as many rows as columns
        cuts[-2:] = [(cuts[-2][0], cuts[-1][1])]
    triangles = []
    for a, b in cuts:
        block[a:b], r = np.linalg.qr(block[a:b])
        triangles.append(r)
    outer = np.linalg.qr(np.vstack(triangles))[0]
    for i, (a, b) in enumerate(cuts):
        block[a:b] = block[a:b] @ outer[i * width : (i + 1) * width]
    return block


def _pieces(rows: DataFrame, block, n: int):
    """(A^T A) block for the sparse rows of A, by as many columns as fit BLOCK_BYTES and by pieces of parts: yields the first
    column, the first part and the piece.  The columns are sent before their pieces come, so the caller may put these in
    their place; columns of a block in Fortran order are sent without a copy."""
    import numpy as np

    sc, piece = rows.sparkSession.sparkContext, PIECE
    step = max(1, BLOCK_BYTES // (8 * max(1, n)))
    for lo in range(0, block.shape[1], step):
        shared = sc.broadcast(np.ascontiguousarray(block[:, lo : lo + step].T))
        width = min(step, block.shape[1] - lo)

        def products(batches, shared=shared, width=width):
            import pyarrow as pa

            b, out = shared.value, np.zeros((width, n))
            for batch in batches:
                cells, x = batch.column(1), batch.column(2).flatten().to_numpy()
                at, ends = cells.flatten().to_numpy(), np.cumsum(cells.value_lengths().to_numpy())
                if not len(at):
                    continue
                starts = np.concatenate([[0], ends[:-1]])
                for column, sums in zip(b, out, strict=True):  # one column at a time has numpy's quick ways
                    y = np.add.reduceat(x * column[at], starts)  # no row of A is empty
                    np.add.at(sums, at, np.repeat(y, ends - starts) * x)
            for p in range(0, n, piece):
                yield pa.RecordBatch.from_arrays([pa.array([p // piece]), pa.array([out[:, p : p + piece].tobytes()], pa.binary())], names=["piece", "t"])

        def sums(batches):
            import pyarrow as pa

            got = {}
            for batch in batches:
                for i, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    t = np.frombuffer(t.as_buffer())
                    got[i] = got[i] + t if i in got else t.copy()
            for i, t in got.items():
                yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([t.tobytes()], pa.binary())], names=["piece", "t"])

        kinds = "piece long, t binary"
        met = rows.mapInArrow(products, kinds).repartition("piece").mapInArrow(sums, kinds)
        for i, t in met.toLocalIterator(prefetchPartitions=True):
            yield lo, i * piece, np.frombuffer(t).reshape(width, -1).T
        shared.destroy()


def _gram(rows: DataFrame, block, n: int):
    """The same by whole columns: yields the first one and the product of as many as fit BLOCK_BYTES."""
    import itertools

    import numpy as np

    for lo, pieces in itertools.groupby(_pieces(rows, block, n), lambda x: x[0]):
        total = None
        for _, at, x in pieces:
            total = np.empty((n, x.shape[1])) if total is None else total
            total[at : at + len(x)] = x
        yield lo, total


def latent_factors(spark: SparkSession, sf_dir: str, rank: int = 16, rounds: int = 4, seed: int = 7) -> tuple[DataFrame, DataFrame]:
    """Items (right factors times singular values) and users (left factors) of the customer-by-part quantities.

    Truncated SVD by subspace iteration: the sparse matrix stays distributed and is written once, with places of parts for
    their keys.  On the driver are a part-by-rank block and pieces of its product, which take its place; a task holds BLOCK_BYTES
    of each.
    Lines of a part that the part table lacks are left out."""
    import numpy as np

    o, li = read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem")
    part = read(spark, sf_dir, "part").select("p_partkey")
    keys = part.distinct().orderBy("p_partkey").toArrow()["p_partkey"].to_numpy()
    n, sc = len(keys), spark.sparkContext
    rank = min(rank, n)
    known = sc.broadcast(keys)

    def placed(batches):
        """Parts by their places; lines of unknown parts, and customers who have no others, are left out."""
        import pyarrow as pa

        for b in batches:
            if b.num_rows:
                key, x = b.column(1).flatten().to_numpy(), b.column(2).flatten().to_numpy()
                at = np.minimum(np.searchsorted(known.value, key), n - 1)
                here = known.value[at] == key
                ends = np.cumsum(b.column(1).value_lengths().to_numpy())
                left = np.diff(np.concatenate([[0], np.cumsum(here)[ends - 1]]))
                offsets = pa.array(np.concatenate([[0], np.cumsum(left[left > 0])]).astype(np.int32))
                lists = [pa.ListArray.from_arrays(offsets, pa.array(y[here])) for y in (at, x)]
                yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(left > 0)), *lists], names=["cust", "at", "x"])

    lines = li.join(o, li.l_orderkey == o.o_orderkey).where("l_partkey is not null").select("o_custkey", "l_partkey", "l_quantity")
    # one shuffle by customer serves both groupings, and places are looked up in whole lists
    cells = lines.repartition("o_custkey").groupBy("o_custkey", "l_partkey").agg(F.sum("l_quantity").cast("double").alias("x")).where("x is not null")
    rows = cells.groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.struct("l_partkey", "x"))).alias("c"))
    rows = scratch.written(rows.select("o_custkey", "c.l_partkey", "c.x").mapInArrow(placed, "cust long, at array<long>, x array<double>"), "quantities")
    # as many parts as the tasks' sums may take, whatever the number of files
    rows = rows.coalesce(min(8, max(4, sc.defaultParallelism)))

    random, block = np.random.default_rng(seed), np.empty((n, rank), order="F")
    for a in range(0, n, QR_ROWS):
        block[a : a + QR_ROWS] = random.standard_normal((min(QR_ROWS, n - a), rank))
    block = np.linalg.qr(block)[0] if n <= QR_ROWS else orthogonal(block)
    for _ in range(rounds):
        for lo, at, product in _pieces(rows, block, n):
            block[at : at + len(product), lo : lo + product.shape[1]] = product
        block = orthogonal(block)
    turned = np.zeros((rank, rank))
    for lo, at, product in _pieces(rows, block, n):
        turned[:, lo : lo + product.shape[1]] += block[at : at + len(product)].T @ product
    squares, basis = np.linalg.eigh(turned)
    values = np.sqrt(np.maximum(squares, 0))
    for a in range(0, n, QR_ROWS):
        block[a : a + QR_ROWS] = block[a : a + QR_ROWS] @ basis
    right = sc.broadcast(block)
    del block

    def users(batches):
        import pyarrow as pa

        for b in batches:
            if b.num_rows:
                cells, x = b.column(1), b.column(2).flatten().to_numpy()
                ends = np.cumsum(cells.value_lengths().to_numpy())
                y = np.add.reduceat(x[:, None] * right.value[cells.flatten().to_numpy()], np.concatenate([[0], ends[:-1]]), axis=0) / np.maximum(values, 1e-9)
                yield pa.RecordBatch.from_arrays([b.column(0), lists(y)], names=["vec_id", "v"])

    def items(batches):
        import pyarrow as pa

        for b in batches:
            key = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([b.column(0), lists(right.value[np.searchsorted(known.value, key)] * values)], names=["vec_id", "v"])

    def lists(y):
        import pyarrow as pa

        return pa.ListArray.from_arrays(np.arange(0, y.size + 1, rank, dtype=np.int32), pa.array(y.ravel()))

    points = "vec_id long, v array<double>"
    made = [scratch.written(part.repartition(sc.defaultParallelism).mapInArrow(items, points), "items"), scratch.written(rows.mapInArrow(users, points), "users")]
    right.destroy()
    return made[0], made[1]


def toy_points(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, list(v)) for i, v in TOY], "vec_id long, v array<double>")


def plane_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points of the first two coordinates of the embeddings."""
    return unit_embeddings(spark, sf_dir).select("vec_id", F.slice("v", 1, 2).alias("v"))


def sample_queries(points: DataFrame, n: int = 20, seed: int = 42) -> DataFrame:
    """The first n points by md5 of id and seed, as queries."""
    at = F.md5(F.concat(F.col("vec_id").cast("string"), F.lit(f":{seed}")))
    return points.orderBy(at, "vec_id").limit(n).select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))


def validate_points(points: DataFrame, d: int) -> DataFrame:
    """Points of d finite coordinates; others are dropped."""
    good = (F.size("v") == d) & ~F.exists("v", lambda x: x.isNull() | F.isnan(x))
    return points.where(F.col("v").isNotNull() & good)
