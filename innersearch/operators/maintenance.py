"""Changes of a written ring index: batches of deletes and adds in folders beside the base files.

The manifest of a batch is written last, so a batch counts once it is whole: one that was lost half-way is written anew, and
one that is replayed is skipped.  Centres, ring width and keys stay as built.  Radii and the greatest norm only grow, so
pruning and both certificates stay sound; counts follow adds and deletes, so radii promised from them hold enough points.
The last ring of a cluster takes all points beyond it.  `ringindex.write` of a loaded index compacts it."""

from __future__ import annotations

import dataclasses
import json

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators import ringindex as R
from innersearch.operators import signcells
from innersearch.sources import scratch

_CELL = ["part", "ikey", "sub"]


def committed(spark: SparkSession, path: str) -> list[str]:
    """Folders of whole batches, in order."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(f"{path}/batch_*/manifest/_SUCCESS")
    found = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(at)
    return sorted(str(x.getPath().getParent().getParent().toString()) for x in found or [])


def _applied(base: DataFrame, batch: DataFrame, gone: DataFrame) -> DataFrame:
    return base.join(scratch.small_side(gone), "vec_id", "left_anti").select(*base.columns).unionByName(batch.select(*base.columns))


def load(spark: SparkSession, path: str) -> R.RingIndex:
    """The base index with all whole batches applied."""
    index = R.load(spark, path)
    for at in committed(spark, path):
        gone = spark.read.parquet(f"{at}/gone")
        narrow, wide = spark.read.schema(R._NARROW).parquet(f"{at}/points_narrow"), spark.read.schema(R._WIDE).parquet(f"{at}/points_wide")
        index = dataclasses.replace(
            index, points=_applied(index.points, narrow, gone), wide=_applied(index.wide, wide, gone),
            parts=spark.read.parquet(f"{at}/parts"), subcells=spark.read.parquet(f"{at}/subcells"),
        )
    return index


def max_norm2(spark: SparkSession, path: str) -> float:
    """Greatest squared norm that any batch has added."""
    return max((json.loads(spark.read.parquet(f"{at}/manifest").first()[0])["maxn2"] for at in committed(spark, path)), default=0.0)


def _keyed(index: R.RingIndex, added: DataFrame) -> DataFrame:
    """Added points with their cluster, ring (the last one is open) and the sub-cell of the nearest pivot (0 in an empty ring)."""
    near = R.assign(added, index.centres)
    ring = F.least(R.ring(F.col("cdist"), index.eps), F.lit(index.factor - 1))
    pivots = index.subcells.groupBy("ikey").agg(F.collect_list(F.struct("sub", "pivot")).alias("pivots"))
    met = near.withColumn("ikey", F.col("part").cast("long") * index.factor + ring).join(F.broadcast(pivots), "ikey", "left")
    choice = F.array_min(F.transform("pivots", lambda x: F.struct(V.dist(F.col("pv"), x["pivot"]).alias("d"), x["sub"].alias("sub"))))["sub"]
    return met.withColumn("sub", F.coalesce(choice, F.lit(0))).drop("pivots")


def _cells(index: R.RingIndex, rows: DataFrame, lost: DataFrame, m: int) -> DataFrame:
    """The sub-cell table after a batch."""
    fresh = rows.groupBy(*_CELL).agg(F.count("*").alias("n_new"), F.array(*[F.round(F.avg(F.col("pv")[i]), 9) for i in range(m)]).alias("mean"))
    both = index.subcells.join(fresh, _CELL, "full").withColumn("pivot", F.coalesce("pivot", "mean"))
    far = rows.join(F.broadcast(both.select(*_CELL, "pivot")), _CELL).groupBy(*_CELL).agg(F.max(V.dist("pv", "pivot")).alias("far"))
    cnt = F.coalesce("cnt", F.lit(0)) + F.coalesce("n_new", F.lit(0)) - F.coalesce("n_gone", F.lit(0))
    new = both.join(far, _CELL, "left").join(lost, _CELL, "left").select(*_CELL, "pivot", F.greatest("radius", "far").alias("radius"), cnt.alias("cnt")).where("cnt > 0")
    before = F.coalesce(F.sum("cnt").over(Window.orderBy("ikey", "sub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return new.select(*_CELL, "pivot", "radius", "cnt", before.cast("long").alias("row_offset"))


def _parts(index: R.RingIndex, rows: DataFrame, cells: DataFrame) -> DataFrame:
    spark = rows.sparkSession
    centres = spark.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(index.centres)], "part int, centre array<double>")
    far = rows.groupBy("part").agg(F.max("cdist").alias("far"))
    held = cells.groupBy("part").agg(F.sum("cnt").alias("cnt"))
    old = index.parts.select("part", "radius")
    return centres.join(held, "part").join(old, "part", "left").join(far, "part", "left").select("part", "centre", F.greatest("radius", "far").alias("radius"), "cnt")


def apply_batch(spark: SparkSession, path: str, batch: int, added: DataFrame, deleted: DataFrame | None = None) -> bool:
    """Writes a batch: deleted(vec_id) go, then added(vec_id, v, pv, n1, n2) come; an added id that lives is replaced.

    An id occurs once among the added (`streaming.events.upsert_points` shows how to keep the last).  Batches are applied in
    the order of their numbers.  False if the batch is there already."""
    at = f"{path}/batch_{batch:09d}"
    done = committed(spark, path)
    if any(x.endswith(f"/batch_{batch:09d}") for x in done):
        return False
    if done and done[-1].rsplit("_", 1)[1] > f"{batch:09d}":
        raise ValueError(f"batch {batch} comes before one that is applied")
    index = load(spark, path)
    gone = added.select("vec_id") if deleted is None else added.select("vec_id").unionByName(deleted.select("vec_id"))
    gone.distinct().write.mode("overwrite").parquet(f"{at}/gone")
    rows = scratch.written(_keyed(index, added), "batch")
    for name, cols in (("points_narrow", ["pv", "n1", "n2"]), ("points_wide", ["v"])):
        ordered = rows.repartitionByRange("ikey", "sub").sortWithinPartitions("ikey", "sub", "vec_id")
        ordered.select(*_CELL, "vec_id", *cols).write.mode("overwrite").partitionBy("part").parquet(f"{at}/{name}")
    lost = index.points.join(scratch.small_side(spark.read.parquet(f"{at}/gone")), "vec_id").groupBy(*_CELL).agg(F.count("*").alias("n_gone"))
    cells = _cells(index, rows, lost, len(index.centres[0]) if index.centres else 0)
    cells.coalesce(1).write.mode("overwrite").parquet(f"{at}/subcells")
    _parts(index, rows, spark.read.parquet(f"{at}/subcells")).coalesce(1).write.mode("overwrite").parquet(f"{at}/parts")
    manifest = json.dumps({"maxn2": float(rows.agg(F.max("n2")).first()[0] or 0.0)})
    spark.createDataFrame([(manifest,)], "manifest string").write.mode("overwrite").parquet(f"{at}/manifest")
    return True


def refreshed(engine, path: str):
    """The engine with the batches under path (that of its ring) applied; sign cells are counted anew from the narrow rows."""
    spark = engine.points.sparkSession
    ring = load(spark, path)
    cells = scratch.written(signcells.build_cells(ring.points, engine.m, "n1" if engine.params.ub_norm == "l1" else "n2").coalesce(1), "sign_cells")
    n = ring.parts.agg(F.sum("cnt")).first()[0] or 0
    return dataclasses.replace(engine, points=ring.points, ring=ring, cells=cells, n=n, maxn2=max(engine.maxn2, max_norm2(spark, path)))
