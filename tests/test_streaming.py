from pyspark.sql import functions as F

from innersearch.sources import vectors as S
from innersearch.streaming import events as E

from .compare import rows_of


def files(spark, sf_dir, tmp_path, order=(0, 1, 2, 3)):
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    n = e.count() // 4 + 1
    path = str(tmp_path / "events")
    for i in order:
        e.where(F.floor(F.col("event_id") / n) == i).coalesce(1).write.mode("append").parquet(path)
    return e, path


def run(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    q.stop()
    return df.sparkSession.table(name)


def test_windows_equal_batch(spark, sf_dir, tmp_path):
    e, path = files(spark, sf_dir, tmp_path)
    out = run(E.windowed(E.read_stream(spark, path, files_per_trigger=10), "tumbling"), "tumbling", "complete")
    assert rows_of(out) == rows_of(E.windowed(e, "tumbling"))


def test_late_rows_are_dropped(spark, sf_dir, tmp_path):
    e, path = files(spark, sf_dir, tmp_path, (0, 1, 3, 2))
    out = run(E.windowed(E.read_stream(spark, path), "tumbling"), "late", "append")
    assert out.agg(F.sum("n")).first()[0] < e.count()


def test_dedup_and_top(spark, sf_dir, tmp_path):
    e, path = files(spark, sf_dir, tmp_path, (0, 0, 1, 2, 3))
    assert run(E.deduplicated(E.read_stream(spark, path, files_per_trigger=10)), "dedup", "append").count() == e.count()
    top = run(E.top_values(E.read_stream(spark, path, files_per_trigger=10), 2), "top", "update")
    want = {r["user_id"]: r["m"] for r in e.groupBy("user_id").agg(F.max("value").alias("m")).collect()}
    assert {r["user_id"]: r["m"] for r in top.groupBy("user_id").agg(F.max(F.col("top")[0]).alias("m")).collect()} == want


def test_stream_search(spark, sf_dir, tmp_path):
    e, path = files(spark, sf_dir, tmp_path)
    points = S.unit_embeddings(spark, sf_dir).persist()
    sink = str(tmp_path / "hits")
    E.stream_search(E.read_stream(spark, path, files_per_trigger=2), points, 50, sink, str(tmp_path / "ck")).awaitTermination(120)
    got = spark.read.parquet(sink).select("qid", "rank", "vec_id").distinct()
    assert rows_of(got) == rows_of(E.search_batch(e, points, 50).select("qid", "rank", "vec_id"))


def test_upserts(spark):
    live = spark.createDataFrame([(1, [1.0]), (2, [2.0])], "vec_id long, v array<double>")
    log = spark.createDataFrame([("del", 1, None, 1), ("add", 1, [5.0], 2), ("add", 3, [3.0], 1), ("del", 2, None, 9)], "op string, vec_id long, v array<double>, ts long")
    assert sorted((r["vec_id"], r["v"]) for r in E.live_points(live, log).collect()) == [(1, [5.0]), (3, [3.0])]
