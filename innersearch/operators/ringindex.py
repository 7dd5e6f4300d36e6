"""The distance-key index and its three-level form: clusters, rings of equal width, sub-cells in a ring.

A point's key is part * C + floor(distance to its centre / eps).  Centres may come from anywhere: radii,
counts and pivots are taken from the final assignment of all points, so pruning loses nothing."""

from __future__ import annotations

import dataclasses
import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators import kmeans
from innersearch.operators.exact import spread
from innersearch.sources import scratch


#: Most sub-cells of an index: their table is what a search broadcasts, whatever the number of points.
MAX_CELLS = 20_000


@dataclasses.dataclass
class RingIndex:
    """points(part, ikey, sub, vec_id, pv, n1, n2), parts(part, centre, radius, cnt), subcells(...).

    A written index has the vectors in a second table, wide(part, ikey, sub, vec_id, v); else points hold them as v."""

    points: DataFrame
    parts: DataFrame
    subcells: DataFrame
    centres: list[list[float]]
    eps: float
    factor: int
    wide: DataFrame | None = None


def assign(points: DataFrame, centres) -> DataFrame:
    near = kmeans.nearest("pv", centres)
    return points.withColumn("near", near).select(*points.columns, F.col("near.part").alias("part"), F.col("near.d").alias("cdist"))


def part_table(assigned: DataFrame, centres) -> DataFrame:
    """part, centre, radius, cnt from the final assignment."""
    spark = assigned.sparkSession
    c = spark.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(centres)], "part int, centre array<double>")
    return assigned.groupBy("part").agg(F.max("cdist").alias("radius"), F.count("*").alias("cnt")).join(F.broadcast(c), "part").select("part", "centre", "radius", "cnt")


def ring_width(radii: list[float], n_key: int) -> float:
    """Mean cluster radius over the number of rings."""
    return round(math.fsum(radii) / max(1, len(radii)) / n_key, 9) or 1.0


def ring(cdist: Column, eps: float) -> Column:
    return F.floor(cdist / F.lit(eps)).cast("long")


def index_key(part: Column, cdist: Column, eps: float, factor: int) -> Column:
    return part.cast("long") * factor + ring(cdist, eps)


def selectivity(k_p: int, n_key: int, k_sp: int) -> float:
    """Share of the points in a sub-cell."""
    return 1 / (k_p * n_key * k_sp)


def params_for(n: int, target_rows: int, k_p: int = 5, k_sp: int = 10) -> tuple[int, int, int]:
    """k_p, n_key, k_sp whose sub-cells hold about target_rows; small sets get fewer of each, large ones MAX_CELLS in all
    (so at 10^9 points a sub-cell is a row group of 50,000)."""
    cells = max(1, min(MAX_CELLS, n // max(1, target_rows)))
    k_p = max(1, min(k_p, cells))
    k_sp = max(1, min(k_sp, math.isqrt(max(1, cells // k_p))))
    return k_p, max(1, cells // (k_p * k_sp)), k_sp


def build_plain(points: DataFrame, centres, eps: float | None = None, n_key: int = 40) -> RingIndex:
    """Clusters and keys only (sub is 0), planned on the points as they are."""
    keyed, parts, eps, factor = _keyed(assign(points, centres), centres, eps, n_key)
    keyed = keyed.withColumn("sub", F.lit(0))
    return RingIndex(keyed, parts, subcell_table(keyed, len(centres[0])), centres, eps, factor)


def build(points: DataFrame, k_p: int = 5, n_key: int = 40, k_sp: int = 10, eps: float | None = None, iters: int = 5, path: str | None = None) -> RingIndex:
    """Clusters, keys and sub-cells of projected points, written under path (None: the shared folder) and read from there."""
    spark = points.sparkSession
    path = path or scratch.path_for(spark, "ring_index")
    centres, _ = kmeans.lloyd(points, "pv", k_p, iters)
    keyed, parts, eps, factor = _keyed(assign(points, centres), centres, eps, n_key)
    split_rings(keyed, k_sp).select("part", "ikey", "sub", "vec_id", "pv", "n1", "n2", "v").write.parquet(f"{path}/keyed")
    table = spark.read.parquet(f"{path}/keyed")
    write(RingIndex(table, parts, subcell_table(table, len(centres[0]) if centres else 0), centres, eps, factor), path)
    return load(spark, path)


def _keyed(assigned: DataFrame, centres, eps: float | None, n_key: int) -> tuple[DataFrame, DataFrame, float, int]:
    """Points with ikey; parts as a table of k_p rows; the ring width; the constant of the keys."""
    table = part_table(assigned, centres)
    rows = table.collect()
    parts = assigned.sparkSession.createDataFrame(rows, table.schema)
    radii = [r["radius"] for r in rows]
    eps = eps or ring_width(radii, n_key)
    factor = int(max(radii, default=0.0) / eps) + 2
    return assigned.withColumn("ikey", index_key(F.col("part"), F.col("cdist"), eps, factor)), parts, eps, factor


def split_rings(keyed: DataFrame, k_sp: int, sample: int = 2000, iters: int = 5) -> DataFrame:
    """Adds `sub`: the nearest of k_sp centres fitted on about `sample` points of each ring, drawn by a hash of the id at
    the ring's rate; only the sample is shuffled."""
    rates = keyed.groupBy("ikey").agg(F.count("*").alias("cnt")).select("ikey", F.least(F.lit(1.0), sample / F.col("cnt")).alias("rate"))
    draw = kmeans.hash_share("vec_id")
    few = keyed.select("ikey", "vec_id", "pv", draw.alias("rn")).join(F.broadcast(rates), "ikey").where("rn <= rate").drop("rate")

    def fit(pdf):
        import numpy as np
        import pandas as pd

        x = np.array(pdf.sort_values(["rn", "vec_id"])["pv"].tolist())
        c = x[:k_sp].copy()
        for _ in range(iters):
            near = ((x[:, None] - c[None]) ** 2).sum(2).argmin(1)
            for j in range(len(c)):
                if (near == j).any():
                    c[j] = x[near == j].mean(0)
        return pd.DataFrame({"ikey": [pdf["ikey"].iloc[0]], "subs": [c.tolist()]})

    subs = few.groupBy("ikey").applyInPandas(fit, "ikey long, subs array<array<double>>")
    choice = F.array_min(F.transform("subs", lambda c, i: F.struct(V.dist(F.col("pv"), c).alias("d"), i.alias("i"))))["i"]
    return keyed.join(F.broadcast(subs), "ikey", "left").withColumn("sub", F.coalesce(choice, F.lit(0))).drop("subs")


def subcell_table(keyed: DataFrame, m: int) -> DataFrame:
    """part, ikey, sub, pivot (mean projection), radius, cnt, row_offset (rows before it in key order).

    Two partial aggregations over the points: means, then the greatest distance from them.  The order of the sub-cells is
    taken on their own table, which the parameters bound."""
    means = [F.round(F.avg(F.col("pv")[i]), 9) for i in range(m)]
    pivots = keyed.groupBy("part", "ikey", "sub").agg(F.count("*").alias("cnt"), F.array(*means).alias("pivot"))
    met = keyed.select("part", "ikey", "sub", "pv").join(F.broadcast(pivots), ["part", "ikey", "sub"])
    cells = met.groupBy("part", "ikey", "sub").agg(F.first("pivot").alias("pivot"), F.max(V.dist("pv", "pivot")).alias("radius"), F.first("cnt").alias("cnt"))
    before = F.coalesce(F.sum("cnt").over(Window.orderBy("ikey", "sub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return cells.select("part", "ikey", "sub", "pivot", "radius", "cnt", before.cast("long").alias("row_offset"))


def candidate_cells(index: RingIndex, balls: DataFrame) -> DataFrame:
    """qid, part, ikey, sub of sub-cells that a ball (qid, qpv, lo, hi) may reach.

    Metadata only, coarse to fine: clusters, then rings of reached clusters (the last is open), then sub-cells."""
    slack = 1e-6
    near = balls.crossJoin(F.broadcast(index.parts)).withColumn("cd", V.dist("qpv", "centre")).where(F.col("cd") <= F.col("radius") + F.col("hi") + slack)
    near = near.select("qid", "qpv", "lo", "hi", "part", "cd")
    cells = near.join(F.broadcast(index.subcells.withColumnRenamed("radius", "s_radius")), "part")
    ring_no = F.col("ikey") - F.col("part") * index.factor
    cells = cells.where((ring_no * index.eps <= F.col("cd") + F.col("hi") + slack) & ((ring_no == index.factor - 1) | ((ring_no + 1) * index.eps >= F.col("cd") - F.col("hi") - slack)))
    d = V.dist("qpv", "pivot")
    return cells.where((d <= F.col("s_radius") + F.col("hi") + slack) & (d >= F.col("lo") - F.col("s_radius") - slack)).select("qid", "part", "ikey", "sub")


def fetch(index: RingIndex):
    """A fetch function for ball search: cells to narrow rows, then the distance test, then the vectors of what is left.

    The cells are sent to the tasks behind a check, and points are tested by whole batches; a point that is left is one row with
    its queries.  These rows are broadcast behind a check too; the point tables are not shuffled then."""

    def run(points: DataFrame, balls: DataFrame, exclude_self: bool = True) -> DataFrame:
        cells = scratch.written(candidate_cells(index, balls), "cells")
        if cells.limit(scratch.BROADCAST_ROWS + 1).count() > scratch.BROADCAST_ROWS:
            return _fetch_joined(index, points, balls, cells, exclude_self)
        test, product = _pairs(balls.select("qid", "qpv", "qv", "lo", "hi").toArrow(), cells.toArrow(), points.sparkSession.sparkContext, exclude_self)
        keys, lists = "part int, ikey long, sub int, vec_id long", "qs array<int>, nears array<double>"
        more = ["v"] if index.wide is None else []
        narrow = points.where("pv is not null").select("part", "ikey", "sub", "vec_id", "pv", *more)
        left = narrow.mapInArrow(test, f"{keys}, {'v array<double>, ' if more else ''}{lists}")
        if index.wide is not None:
            left = scratch.written(left, "in_ball")
            pairs = left.agg(F.sum(F.size("qs"))).first()[0] or 0
            left = index.wide.join(F.broadcast(left) if pairs <= scratch.BROADCAST_ROWS else left.hint("merge"), ["part", "ikey", "sub", "vec_id"])
        met = left.select("vec_id", "v", "qs", "nears").mapInArrow(product, "qid long, vec_id long, near double, lo double, hi double, ip double")
        # distances are rounded as everywhere else, then held against the ball
        return met.withColumn("pdist", F.round("near", 9)).where("pdist <= hi and pdist > lo").select("qid", "vec_id", "pdist", "ip")

    return run


#: Most pairs of points and queries that a task makes at once.
PAIRS = 2**18


def _pairs(balls, cells, sc, exclude_self: bool):
    """Functions of record batches: the points in balls (a little wider than they are) with their queries, and the products of such
    pairs.  Sums are made in order, as vector expressions do."""
    import numpy as np

    qids = balls["qid"].to_numpy()
    wide = [np.array(balls[c].to_pylist(), np.float64).reshape(len(qids), -1).T.copy() for c in ("qpv", "qv")]
    lo, hi = (balls[c].to_numpy() for c in ("lo", "hi"))
    subs = int(max(cells["sub"].to_numpy(), default=0)) + 1
    code = cells["ikey"].to_numpy() * subs + cells["sub"].to_numpy()
    by_id = np.argsort(qids, kind="stable")
    asked = by_id[np.searchsorted(qids, cells["qid"].to_numpy(), sorter=by_id)].astype(np.int32)
    order = np.argsort(code, kind="stable")
    codes, starts = np.unique(code[order], return_index=True)
    shared = sc.broadcast((qids, *wide, lo, hi, subs, codes, np.append(starts, len(code)), asked[order]))
    most = PAIRS

    def slices(counts):
        """Cuts of rows whose pairs are about `most`."""
        at, ends = 0, np.cumsum(counts)
        while at < len(counts):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
            yield at, to
            at = to

    def test(batches):
        import pyarrow as pa

        qids, qpv, _, lo, hi, subs, codes, starts, asked = shared.value
        for b in batches:
            if not b.num_rows or not len(codes):
                continue
            sub, ids = b.column(2).to_numpy(), b.column(3).to_numpy()
            code = np.where(sub < subs, b.column(1).to_numpy() * subs + sub, -1)
            cell = np.minimum(np.searchsorted(codes, code), len(codes) - 1)
            counts = np.where((codes[cell] == code) & (sub < subs), starts[cell + 1] - starts[cell], 0)
            pv = b.column(4).flatten().to_numpy().reshape(b.num_rows, -1).T.copy()
            for x, y in slices(counts):
                n = counts[x:y]
                i = np.repeat(np.arange(x, y), n)
                j = asked[np.repeat(starts[cell[x:y]] - np.cumsum(n) + n, n) + np.arange(len(i))]
                d2 = np.zeros(len(i))
                for p, q in zip(pv, qpv, strict=True):
                    gap = p.take(i) - q.take(j)
                    d2 += gap * gap
                near = np.sqrt(d2)
                keep = (near <= hi[j] + 1e-8) & (near > lo[j] - 1e-8)
                if exclude_self:
                    keep &= ids[i] != qids[j]
                kept = np.bincount(i[keep] - x, minlength=y - x)
                rows = np.nonzero(kept)[0]
                if len(rows):
                    ends = pa.array(np.concatenate([[0], np.cumsum(kept[rows])]).astype(np.int32))
                    lists = [pa.ListArray.from_arrays(ends, pa.array(z[keep])) for z in (j, near)]
                    names = [*b.schema.names[:4], *b.schema.names[5:], "qs", "nears"]
                    at = pa.array(rows + x)
                    yield pa.RecordBatch.from_arrays([*(b.column(c).take(at) for c in range(b.num_columns) if c != 4), *lists], names=names)

    def product(batches):
        import pyarrow as pa

        qids, _, qv, lo, hi = shared.value[:5]
        for b in batches:
            if not b.num_rows:
                continue
            ids, counts = b.column(0).to_numpy(), b.column(2).value_lengths().to_numpy()
            v = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1).T.copy()
            j_all, near = b.column(2).flatten().to_numpy(), b.column(3).flatten().to_numpy()
            ends = np.concatenate([[0], np.cumsum(counts)])
            for x, y in slices(counts):
                i, j = np.repeat(np.arange(x, y), counts[x:y]), j_all[ends[x] : ends[y]]
                ip = np.zeros(len(i))
                for p, q in zip(v, qv, strict=True):
                    ip += p.take(i) * q.take(j)
                cols = (qids[j], ids[i], near[ends[x] : ends[y]], lo[j], hi[j], ip)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["qid", "vec_id", "near", "lo", "hi", "ip"])

    return test, product


def _fetch_joined(index: RingIndex, points: DataFrame, balls: DataFrame, cells: DataFrame, exclude_self: bool) -> DataFrame:
    """The same by joins, for more cells than are sent to the tasks."""
    got = points.join(cells.hint("merge"), ["part", "ikey", "sub"]).join(F.broadcast(balls.select("qid", "qpv", "lo", "hi")), "qid")
    if exclude_self:
        got = got.where("vec_id != qid")
    got = got.withColumn("pdist", V.dist("pv", "qpv")).where("pdist <= hi and pdist > lo")
    vectors = F.broadcast(balls.select("qid", "qv"))
    if index.wide is None:
        return got.select("qid", "vec_id", "pdist", "v").join(vectors, "qid").select("qid", "vec_id", "pdist", V.dot("v", "qv").alias("ip"))
    left = scratch.small_side(scratch.written(got.select("qid", "part", "ikey", "sub", "vec_id", "pdist"), "in_ball"))
    met = index.wide.join(left, ["part", "ikey", "sub", "vec_id"]).join(vectors, "qid")
    return met.select("qid", "vec_id", "pdist", V.dot("v", "qv").alias("ip"))


def enclosing(index: RingIndex, queries: DataFrame, k: int, exclude_self: bool = True) -> DataFrame:
    """qid, reach: a radius within which the sub-cells promise k points other than the query (null if there are fewer).

    Metadata only: sub-cells by the greatest distance that a point of theirs may have, until their counts suffice."""
    need = k + int(exclude_self)
    far = F.round(V.dist("qpv", "pivot") + F.col("radius") + 1e-6, 9)
    both = queries.select("qid", "qpv").crossJoin(F.broadcast(index.subcells)).select("qid", "ikey", "sub", "cnt", far.alias("far"))
    run = F.sum("cnt").over(Window.partitionBy("qid").orderBy("far", "ikey", "sub").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("run", run).groupBy("qid").agg(F.min(F.when(F.col("run") >= need, F.col("far"))).alias("reach"))


def fetch_plain(index: RingIndex, balls: DataFrame) -> DataFrame:
    """qid, vec_id, pdist by key intervals alone."""
    near = balls.crossJoin(F.broadcast(index.parts)).withColumn("cd", V.dist("qpv", "centre")).where("cd <= radius + hi + 1e-6")
    lo = F.least(F.lit(index.factor - 1), F.greatest(F.lit(0), F.floor((F.col("cd") - F.col("hi") - 1e-6) / index.eps)))
    spans = near.select("qid", "qpv", "hi", (F.col("part") * index.factor + lo).alias("key_lo"), (F.col("part") * index.factor + F.least(F.lit(index.factor - 1), F.floor((F.col("cd") + F.col("hi") + 1e-6) / index.eps))).alias("key_hi"))
    met = spread(index.points).join(F.broadcast(spans), F.col("ikey").between(F.col("key_lo"), F.col("key_hi")))
    return met.withColumn("pdist", V.dist("pv", "qpv")).where("pdist <= hi and vec_id != qid").select("qid", "vec_id", "pdist")


def write(index: RingIndex, path: str) -> None:
    """Narrow and wide tables in key order, partitioned by cluster, and the metadata tables."""
    import json

    order = index.points.repartitionByRange("ikey", "sub").sortWithinPartitions("ikey", "sub", "vec_id")
    order.select("part", "ikey", "sub", "vec_id", "pv", "n1", "n2").write.partitionBy("part").parquet(f"{path}/points_narrow")
    vectors = order if index.wide is None else index.wide.repartitionByRange("ikey", "sub").sortWithinPartitions("ikey", "sub", "vec_id")
    vectors.select("part", "ikey", "sub", "vec_id", "v").write.partitionBy("part").parquet(f"{path}/points_wide")
    index.parts.write.parquet(f"{path}/parts")
    index.subcells.coalesce(1).write.parquet(f"{path}/subcells")
    manifest = json.dumps({"eps": index.eps, "factor": index.factor, "centres": index.centres, "format_version": 2})
    index.points.sparkSession.createDataFrame([(manifest,)], "manifest string").write.parquet(f"{path}/manifest")


_NARROW = "ikey long, sub int, vec_id long, pv array<double>, n1 double, n2 double, part int"
_WIDE = "ikey long, sub int, vec_id long, v array<double>, part int"


def load(spark: SparkSession, path: str) -> RingIndex:
    import json

    m = json.loads(spark.read.parquet(f"{path}/manifest").first()[0])
    narrow, wide = spark.read.schema(_NARROW).parquet(f"{path}/points_narrow"), spark.read.schema(_WIDE).parquet(f"{path}/points_wide")
    return RingIndex(narrow, spark.read.parquet(f"{path}/parts"), spark.read.parquet(f"{path}/subcells"), m["centres"], m["eps"], m["factor"], wide)
