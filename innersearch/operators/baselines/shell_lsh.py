"""Shell LSH: concentric shells by norm, a lossless lift in each, and query-aware collision counting."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.functions import transforms
from innersearch.functions import vectors as V
from innersearch.operators.exact import spread, top_k
from innersearch.operators.projection import gaussian_matrix, projected, summed
from innersearch.sources import scratch

RATIO, BASE, LEVELS = 0.75, 2.0, 8


def width(c0: float = BASE) -> float:
    """Bucket width at radius 1."""
    return math.sqrt(8 * c0 * c0 * math.log(c0) / (c0 * c0 - 1))


def _normal(x: float) -> float:
    return (1 + math.erf(x / math.sqrt(2))) / 2


def params(n: int, c0: float = BASE, delta: float = 1 / math.e) -> dict[str, float]:
    """Hash functions and collision threshold from the error probability and 100 / n false positives."""
    w = width(c0)
    p1, p2 = 2 * _normal(w / 2) - 1, 2 * _normal(w / (2 * c0)) - 1
    beta = min(1.0, 100 / max(1, n))
    a, b = math.sqrt(math.log(2 / beta)), math.sqrt(math.log(1 / delta))
    eta = a / b if b else 1.0
    alpha = (eta * p1 + p2) / (1 + eta)
    k = max(1, math.ceil((a + b) ** 2 / (2 * (p1 - p2) ** 2)))
    return {"w": w, "p1": p1, "p2": p2, "functions": k, "threshold": max(1, math.ceil(alpha * k)), "alpha": alpha}


def shells(points: DataFrame, ratio: float = RATIO) -> DataFrame:
    """points with norm and shell: 0 holds norms in (ratio * M, M], 1 the next, ..., at most 60."""
    p = points.withColumn("norm", F.round(V.l2("v"), 9))
    top = p.agg(F.max("norm").alias("top"))
    s = F.floor(F.log(F.col("norm") / F.col("top")) / math.log(ratio) + 1e-9).cast("int")
    return p.crossJoin(F.broadcast(top)).withColumn("shell", F.when(F.col("norm") > 0, F.least(F.lit(60), s)).otherwise(60)).drop("top")


def build(points: DataFrame, d: int, ratio: float = RATIO, seed: int = 42) -> DataFrame:
    """vec_id, v, norm, shell, bound (greatest norm of the shell), as many hashes of the lifted point as its number asks for."""
    functions = params(points.count())["functions"]
    s = shells(spread(points), ratio)
    bound = s.groupBy("shell").agg(F.max("norm").alias("bound"))
    lifted = s.join(F.broadcast(bound), "shell").withColumn("u", transforms.lift_point(F.col("v"), F.col("bound") * F.col("bound")))
    return summed(lifted, "u", gaussian_matrix(functions, d + 1, seed), "h").drop("u")


def hashed(queries: DataFrame, d: int, functions: int, seed: int = 42) -> DataFrame:
    q = queries.withColumn("qu", F.concat(V.normalize("qv"), F.array(F.lit(0.0))))
    return q.withColumn("qh", projected("qu", gaussian_matrix(functions, d + 1, seed))).withColumn("qnorm", V.l2("qv"))


def gaps() -> Column:
    """Distances of a point's hashes from a query's, which is lifted to the point's shell."""
    return F.zip_with("h", "qh", lambda a, b: F.abs(a - b * F.col("bound")))


def reach(w: float, level: Column | int, c0: float = BASE) -> Column:
    """Half of a bucket's width at a level."""
    return w * (F.col("bound") / 50) * F.pow(F.lit(c0), level) / 2


def levels(index: DataFrame, queries: DataFrame, d: int, n: int, c0: float = BASE, seed: int = 42) -> tuple[DataFrame, list]:
    """A written table of the index with `levels`, a byte for each query of the list: the first level at which enough hashes
    collide (LEVELS if at none), LEVELS + 1 for the query's own point.

    As many hashes collide as asked for once the gap of that rank is within reach."""
    import numpy as np

    by = params(n, c0)
    need, w = by["threshold"], by["w"]
    asked = hashed(queries, d, by["functions"], seed).select("qid", "qv", "qh", "qnorm").orderBy("qid").toArrow().to_pylist()
    qids, qh = np.array([r["qid"] for r in asked], np.int64), np.array([r["qh"] for r in asked])
    shared = index.sparkSession.sparkContext.broadcast((qids, qh))
    grow, top = [c0**j for j in range(LEVELS)], LEVELS
    schema = "vec_id long, v array<double>, shell int, bound double, levels binary"

    def run(batches):
        import pyarrow as pa

        qids, qh = shared.value
        step = max(1, 2**21 // max(1, qh.size))
        for b in batches:
            ids, bound = b.column(0).to_numpy(), b.column(3).to_numpy()
            h, out = b.column(4).flatten().to_numpy().reshape(b.num_rows, -1), []
            for at in range(0, b.num_rows, step):
                bd = bound[at : at + step, None]
                gap = np.partition(np.abs(h[at : at + step, None] - qh[None] * bd[:, :, None]), need - 1, axis=2)[:, :, need - 1]
                level = sum((gap > w * (bd / 50) * g / 2).astype(np.uint8) for g in grow)  # reach grows with the level
                level[ids[at : at + step, None] == qids[None]] = top + 1
                out += [x.tobytes() for x in level]
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(out, pa.binary())], names=["vec_id", "v", "shell", "bound", "levels"])

    got = spread(index.select("vec_id", "v", "shell", "bound", "h")).mapInArrow(run, schema)
    return scratch.written(got, "levels"), asked


def last_levels(leveled: DataFrame, asked: list, k: int) -> dict:
    """By shell, the level up to which each query reads it: the one that brings k + 100 candidates (-1: none is there)."""
    import numpy as np

    nq, high = len(asked), LEVELS

    def run(batches):
        import pyarrow as pa

        total = {}
        for b in batches:
            shell = b.column(0).to_numpy()
            level = np.frombuffer(b"".join(b.column(1).to_pylist()), np.uint8).reshape(b.num_rows, nq)
            for s in np.unique(shell):
                one = level[shell == s]
                total[s] = total.get(s, 0) + np.array([(one == j).sum(0) for j in range(high + 1)], np.int64)
        for s, x in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([int(s)], pa.int32()), pa.array([x.tobytes()], pa.binary())], names=["shell", "counts"])

    total = {}
    for s, x in leveled.select("shell", "levels").mapInArrow(run, "shell int, counts binary").toLocalIterator():
        total[s] = total.get(s, 0) + np.frombuffer(x, np.int64).reshape(high + 1, nq)
    last = {}
    for s, x in total.items():
        before = np.cumsum(x, 0) - x
        read = (x > 0) & (before < k + 100)
        last[s] = np.where(read.any(0), high - np.argmax(read[::-1], 0), -1).astype(np.int8)
    return last


def products(leveled: DataFrame, asked: list, last: dict, best: int | None = None) -> DataFrame:
    """qid, vec_id, shell, last, ip of the points read; with `best`, a batch passes on that many of a query and shell at least."""
    import numpy as np

    shared = leveled.sparkSession.sparkContext.broadcast((np.array([r["qid"] for r in asked], np.int64), np.array([r["qv"] for r in asked]), last))

    def run(batches):
        import pyarrow as pa

        qids, q, last = shared.value
        for b in batches:
            ids, shell = b.column(0).to_numpy(), b.column(2).to_numpy()
            v = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
            level = np.frombuffer(b"".join(b.column(3).to_pylist()), np.uint8).reshape(b.num_rows, -1)
            for s in np.unique(shell):
                rows = np.nonzero(shell == s)[0]
                ip = np.zeros((len(qids), len(rows)))
                for x, y in zip(v[rows].T, q.T, strict=True):  # summed in order, as vector expressions do
                    ip += y[:, None] * x[None]
                ip[level[rows].T.astype(np.int16) > last[s][:, None]] = -np.inf
                keep = np.isfinite(ip)
                if best and len(rows) > best:
                    keep &= ip >= np.partition(ip, len(rows) - best, axis=1)[:, len(rows) - best, None]  # ties stay
                j, i = np.nonzero(keep)
                yield pa.RecordBatch.from_arrays([pa.array(qids[j]), pa.array(ids[rows[i]]), pa.array(np.full(len(j), s, np.int32)), pa.array(last[s][j].astype(np.int32)), pa.array(ip[j, i])], names=["qid", "vec_id", "shell", "last", "ip"])

    return leveled.select("vec_id", "v", "shell", "levels").mapInArrow(run, "qid long, vec_id long, shell int, last int, ip double")


def unmasked(read: DataFrame, leveled: DataFrame, asked: list, last: dict, k: int) -> DataFrame:
    """The rows of shells whose bound times |q| can beat the k-th best of those before."""
    from pyspark.sql import Window

    # the k-th best of the shells so far is at least the k-th best found in any one of them
    kth = Window.partitionBy("qid", "shell").orderBy(F.desc("ip"), "vec_id")
    best = read.withColumn("rn", F.row_number().over(kth)).where(F.col("rn") == k).select("qid", "shell", "ip")
    bounds = dict(leveled.select("shell", "bound").distinct().collect())
    rows = [(r["qid"], s, bounds[s], r["qnorm"]) for s, x in last.items() for r, y in zip(asked, x, strict=True) if y >= 0]
    bound = read.sparkSession.createDataFrame(rows, "qid long, shell int, bound double, qnorm double")
    run = F.max("ip").over(Window.partitionBy("qid").orderBy("shell").rowsBetween(Window.unboundedPreceding, -1))
    open_ = bound.join(best, ["qid", "shell"], "left").withColumn("so_far", run).where("so_far is null or so_far < bound * qnorm").select("qid", "shell")
    return read.join(open_, ["qid", "shell"], "left_semi").select("qid", "vec_id", "shell", "last", "ip")


def reads(index: DataFrame, queries: DataFrame, d: int, n: int, k: int = 10, c0: float = BASE, seed: int = 42, best: int | None = None) -> DataFrame:
    """qid, vec_id, shell, last, ip of the points read: `last` is the level up to which a shell is read.

    Radius levels grow by c0 from a hundredth of the shell's diameter; a point is a candidate of the first level at which
    enough hashes collide; a shell is read up to the level that brings k + 100 candidates.  Shells after the one whose bound
    times |q| cannot beat the k-th best are masked, by a running count over shells.

    Levels come from the hashes alone, a byte a pair; products are made for the candidates only."""
    leveled, asked = levels(index, queries, d, n, c0, seed)
    if not asked:
        return queries.select("qid", F.col("qid").alias("vec_id"), F.lit(0).alias("shell"), F.lit(0).alias("last"), F.lit(0.0).alias("ip"))
    last = last_levels(leveled, asked, k)
    return unmasked(scratch.written(products(leveled, asked, last, best), "products"), leveled, asked, last, k)


def search(index: DataFrame, queries: DataFrame, d: int, n: int, k: int = 10, c0: float = BASE, seed: int = 42) -> DataFrame:
    """qid, rank, vec_id, ip, after the shell rule; only the best of a shell are needed for it."""
    return top_k(reads(index, queries, d, n, k, c0, seed, k), k)


def table_pages(index: DataFrame, queries: DataFrame, read: DataFrame, d: int, n: int, page: int, c0: float = BASE, seed: int = 42) -> DataFrame:
    """qid, index_pages: each function has a table of (hash, id) in hash order for each shell, 16 bytes an entry; a query reads
    the run of entries within reach at the last level of a shell, which is a page more than its entries fill at most."""
    import numpy as np

    by = params(n, c0)
    functions, per_page, w = by["functions"], page // 16, by["w"]
    rows = hashed(queries, d, functions, seed).select("qid", "qh").toArrow()
    qids, qh = rows["qid"].to_pylist(), np.array(rows["qh"].to_pylist())
    place, asked = {x: i for i, x in enumerate(qids)}, {}
    for qid, shell, last in read.select("qid", "shell", "last").distinct().collect():  # of a bounded batch of queries
        asked.setdefault(shell, []).append((place[qid], float(c0) ** last))
    asked = {s: (np.array([i for i, _ in x]), np.array([g for _, g in x])) for s, x in asked.items()}
    shared = index.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), qh, asked))

    def run(batches):
        import pyarrow as pa

        qids, qh, asked = shared.value
        total = {}
        for b in batches:
            shell, bound = b.column(0).to_numpy(), b.column(1).to_numpy()
            h = b.column(2).flatten().to_numpy().reshape(b.num_rows, -1)
            for s in np.unique(shell).tolist():
                if s not in asked:
                    continue
                at, grow = asked[s]
                inside, step = total.setdefault(s, np.zeros((len(at), functions), np.int64)), max(1, 2**18 // (len(at) * functions))
                mine = np.nonzero(shell == s)[0]
                for lo in range(0, len(mine), step):
                    x = mine[lo : lo + step]
                    gap = np.abs(h[x][:, None] - qh[at][None] * bound[x, None, None])
                    reach = w * (bound[x, None] / 50) * grow[None] / 2
                    inside += (gap <= reach[:, :, None]).sum(0)
        for s, x in total.items():
            lists = pa.ListArray.from_arrays(np.arange(0, x.size + 1, functions, dtype=np.int32), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(qids[asked[s][0]]), pa.array(np.full(len(x), s, np.int32)), lists], names=["qid", "shell", "inside"])

    runs = spread(index.select("shell", "bound", "h")).mapInArrow(run, "qid long, shell int, inside array<long>")
    tables = runs.select("qid", "shell", F.posexplode("inside").alias("f", "x")).groupBy("qid", "shell", "f").agg(F.sum("x").alias("x"))
    return tables.groupBy("qid").agg(F.sum(F.floor(F.col("x") / per_page) + 1).cast("long").alias("index_pages"))
