"""Streams of events: windows, stream-static search, joins, stateful top-k, and index maintenance."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators.exact import top_k
from innersearch.sources import scratch

EVENT_SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE = "30 minutes"


def read_stream(spark: SparkSession, path: str, schema: str = EVENT_SCHEMA, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """start, end, n, mean_value of tumbling, sliding or session windows (batch or stream)."""
    w = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "10 minutes")}[kind]
    e = events.withWatermark("ts", LATE) if events.isStreaming else events
    keys = [w.alias("w"), "user_id"] if kind == "session" else [w.alias("w")]
    out = e.groupBy(*keys).agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean_value"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *(["user_id"] if kind == "session" else []), "n", "mean_value")


def event_queries(events: DataFrame, points: DataFrame, n: int) -> DataFrame:
    """event_id, ts, qid, qv: every event asks with the vector its user maps to (stream-static join)."""
    return events.withColumn("qid", F.col("user_id") % n).join(points.select(F.col("vec_id").alias("qid"), F.col("v").alias("qv")), "qid").select("event_id", "ts", "qid", "qv")


def search_batch(events: DataFrame, points: DataFrame, n: int, k: int = 5) -> DataFrame:
    """Answers of the users of a micro-batch, each user searched once."""
    users = event_queries(events, points, n).select("qid", "qv").dropDuplicates(["qid"])
    pairs = points.crossJoin(F.broadcast(users)).where("vec_id != qid").select("qid", "vec_id", V.dot("v", "qv").alias("ip"))
    return top_k(pairs, k)


def stream_search(events: DataFrame, points: DataFrame, n: int, sink: str, checkpoint: str, k: int = 5):
    """Runs search_batch on every micro-batch and appends the hits to Parquet; a batch that is replayed
    overwrites its own folder, so the sink is exactly once."""

    def each(batch: DataFrame, epoch: int) -> None:
        search_batch(batch, points, n, k).withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{sink}/epoch={epoch}")

    return events.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def click_then(events: DataFrame, first: str, second: str, within: str = "10 minutes") -> DataFrame:
    """Pairs of events of a user, second within the time after first (interval join, batch or stream)."""
    a, b = events, events
    if events.isStreaming:
        a, b = events.withWatermark("ts", LATE), events.withWatermark("ts", LATE)
    a = a.where(F.col("event_type") == first).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = b.where(F.col("event_type") == second).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    return a.join(b, (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}")))


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def top_values(events: DataFrame, k: int = 3) -> DataFrame:
    """user_id, top: the k greatest values of a user so far (stateful; at most k doubles a user are kept)."""

    def step(key, frames, state):
        import pandas as pd

        top = list(state.get[0]) if state.exists else []
        for pdf in frames:
            top = sorted([*top, *pdf["value"].dropna()], reverse=True)[:k]
        state.update((top,))
        yield pd.DataFrame({"user_id": [key[0]], "top": [top]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, top array<double>", "top array<double>", "update", "NoTimeout")


def upsert_points(live: DataFrame, changes: DataFrame) -> DataFrame:
    """The live points after a batch of changes(op, vec_id, v, ts): the last change of a vec_id counts.

    Certificates stay valid if the caller keeps the greatest norm it has ever seen: it only grows."""
    last = changes.groupBy("vec_id").agg(F.max_by(F.struct("op", "v"), "ts").alias("c"))
    kept = live.join(last.select("vec_id"), "vec_id", "left_anti")
    return kept.unionByName(last.where("c.op = 'add'").select("vec_id", F.col("c.v").alias("v")))


def append_points(changes: DataFrame, path: str, checkpoint: str):
    """Appends a stream of changes to the change log under path."""
    return changes.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def index_changes(changes: DataFrame, path: str, matrix, checkpoint: str):
    """Applies a stream of changes(op, vec_id, v, ts) to the ring index under path, a batch for each micro-batch; of an id's
    changes in one micro-batch the last counts.  A replayed micro-batch is skipped, so an index has one checkpoint folder."""
    from innersearch.operators import maintenance, projection

    def put(batch: DataFrame, number: int) -> None:
        last = batch.groupBy("vec_id").agg(F.max_by(F.struct("op", "v"), "ts").alias("c"))
        last = scratch.written(last.select("vec_id", "c.op", "c.v"), "changes")
        added = projection.project_points(last.where("op = 'add'").select("vec_id", "v"), matrix)
        maintenance.apply_batch(batch.sparkSession, path, number, added, last.where("op != 'add'"))

    return changes.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def live_points(base: DataFrame, log: DataFrame) -> DataFrame:
    """Base points with the change log applied (tombstones by anti join)."""
    return upsert_points(base, log)
