"""Accuracy and cost measures."""

from __future__ import annotations

import contextlib
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def by_rank(hits: DataFrame, exact: DataFrame) -> DataFrame:
    """qid, rank, ip, exact_ip of equal ranks."""
    e = exact.select("qid", "rank", F.col("ip").alias("exact_ip"))
    return e.join(hits.select("qid", "rank", "ip"), ["qid", "rank"], "left")


def overall_ratio(hits: DataFrame, exact: DataFrame) -> DataFrame:
    """qid, ratio (mean over ranks with a positive exact product), n_undefined."""
    r = F.when(F.col("exact_ip") > 0, F.col("ip") / F.col("exact_ip"))
    return by_rank(hits, exact).groupBy("qid").agg(F.avg(r).alias("ratio"), F.sum((F.col("exact_ip") <= 0).cast("long")).alias("n_undefined"))


def recall(hits: DataFrame, exact: DataFrame) -> DataFrame:
    """qid, recall: share of the exact answers that are among the hits."""
    both = exact.select("qid", "vec_id").join(hits.select("qid", "vec_id").withColumn("hit", F.lit(1)), ["qid", "vec_id"], "left")
    return both.groupBy("qid").agg((F.count("hit") / F.count("*")).alias("recall"))


def is_c_approx(hits: DataFrame, exact: DataFrame, c: float) -> DataFrame:
    return by_rank(hits, exact).withColumn("ok", F.coalesce(F.col("ip") >= c * F.col("exact_ip"), F.lit(False)))


def guarantee_rate(hits: DataFrame, exact: DataFrame, c: float) -> DataFrame:
    """rate: share of queries whose first answer is c-approximate."""
    return is_c_approx(hits, exact, c).where("rank = 1").agg(F.avg(F.col("ok").cast("double")).alias("rate"))


def index_size(path: str, spark) -> int:
    """Bytes of the files under a path, of any file system Spark reaches."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return int(p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength())


@contextlib.contextmanager
def timed(out: dict, name: str):
    began = time.perf_counter()
    yield
    out[name] = time.perf_counter() - began


def _stages(spark) -> list:
    """Stages that the status store keeps, once all events of finished tasks are in it."""
    sc, jvm = spark.sparkContext, spark.sparkContext._jvm
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    none = sc._gateway.new_array(jvm.double, 0)
    found = sc._jsc.sc().statusStore().stageList(None, False, False, none, jvm.java.util.ArrayList())
    return [found.apply(i) for i in range(found.size())]


@contextlib.contextmanager
def metered(spark, out: dict):
    """Fills out with total_seconds (wall time, reading the index files included) and cpu_seconds (executor threads, that is
    without Python workers) of what runs inside.  Nothing else may run in the session meanwhile.

    Stages are told by their ids; the status store must keep all stages of a search (1000 by default)."""
    last = max((s.stageId() for s in _stages(spark)), default=-1)
    began = time.perf_counter()
    yield
    out["total_seconds"] = time.perf_counter() - began
    out["cpu_seconds"] = sum(s.executorCpuTime() for s in _stages(spark) if s.stageId() > last) / 1e9
