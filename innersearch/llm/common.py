"""Shared helpers: scratch tables in the cluster's shared folder, word splitting, component labels."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words, and the pattern of a word.
SPACES = " \t\n\x0b\x0c\r"
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir.  A local default is used only by a local master."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = "/tmp/checkpoints"
    return root


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder; it is deleted when the driver's JVM ends."""
    path = f"{scratch_root(spark)}/innersearch/{uuid.uuid4().hex}/{name}"
    jvm = spark.sparkContext._jvm
    hpath = jvm.org.apache.hadoop.fs.Path(path)
    hpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hpath)
    return path


def materialize(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Writes df to the shared folder and reads it back: cuts the lineage so that a lost executor
    costs at most one stage, and lets several jobs share one computation."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Most rows of a narrow table that are broadcast; a larger one is joined by a shuffle.
BROADCAST_ROWS = 2_000_000


def small_side(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """df, marked for broadcast if it has at most `limit` (narrow) rows, else for a sort-merge join."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df.hint("merge")


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col), F.lit(""))


def lower_ascii(col: Column) -> Column:
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def fresh(columns: list[str], name: str) -> str:
    """A column name for own use that clashes with none of `columns`, whatever their case."""
    taken, name = {c.lower() for c in columns}, f"__{name}"
    while name.lower() in taken:
        name = f"_{name}"
    return name


def columns_of(df: DataFrame) -> list[Column]:
    return [F.col(f"`{c}`") for c in df.columns]


def components(edges: DataFrame, max_rounds: int = 1_000) -> DataFrame:
    """Connected components of edges(a, b): returns (node, label), label the smallest node reached.
    Nodes are of any type that has an order and equality.

    Alternates the large-star and small-star contractions; each round is two partial aggregations
    and two joins on the node id (AQE splits a hot node), and is written to the shared folder.
    Stops when a round leaves the edge set unchanged, after O(log^2) rounds; max_rounds is out of reach."""

    def star(e: DataFrame, small: bool) -> DataFrame:
        both = e if small else e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("k"), F.least("a", "m").alias("m"))
        met = both.join(least, F.col("a") == F.col("k"))
        if small:  # a > b holds: hang a and its smaller neighbours on the least of them
            out = met.select(F.explode(F.array("a", "b")).alias("a"), F.col("m").alias("b"))
        else:
            out = met.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        return out.where(F.col("a") != F.col("b")).distinct()

    def summary(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    now = materialize(
        edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(),
        "edges",
    )
    seen = summary(now)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        now = materialize(star(star(now, False), True), "edges")
        was, seen = seen, summary(now)
        if was == seen:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("a").alias("node"), F.col("b").alias("label")).unionByName(now.select("b", "b").distinct().toDF("node", "label"))


#: Texts are handed to numpy in slices of about this many bytes, so that a worker's arrays stay small.
SLICE_BYTES = 1_000_000


#: Most bytes of an Arrow batch on its way to a Python worker (one row may be more); the JVM and the worker hold a few each.
BATCH_BYTES = 4_000_000


def bound_batches(spark: SparkSession) -> None:
    """Bounds Arrow batches by bytes, for 10,000 texts may be any size; a smaller bound of the session stays.
    The bound is read when the plan runs, so it is not put back.  Results do not depend on it."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(name)
    if not now.isdigit() or int(now) > BATCH_BYTES:
        spark.conf.set(name, str(BATCH_BYTES))


def release() -> None:
    """Gives the memory that Arrow and the C library keep for later back to the system: workers are used again."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def tidy(run):
    """A function for mapInArrow that releases memory when its task ends."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


def text_slices(texts, slice_bytes: int = SLICE_BYTES):
    """(first row, end row) of slices of an Arrow large_binary array of about slice_bytes, at least one row each."""
    import numpy as np

    ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset + 1 : texts.offset + len(texts) + 1] if len(texts) else []
    at = 0
    while at < len(texts):
        begun = ends[at - 1] if at else ends[0] - len(texts[0].as_buffer() or b"")
        end = max(at + 1, int(np.searchsorted(ends, begun + slice_bytes, "right")))
        yield at, end
        at = end


def annotate(docs: DataFrame, keep: list[str], added: str, make, slice_bytes: int = SLICE_BYTES, also: tuple[str, ...] = ()) -> DataFrame:
    """Columns `keep` of docs and the columns of the DDL string `added`, computed from the texts.

    make() is called once a task and returns a function from a list of UTF-8 texts (None: null) and lists of the values of the
    columns `also` to a list of column values (lists), one for each added column.  Texts are handed over in slices of
    about slice_bytes, so memory is bounded by a slice or the longest single text."""
    import pyarrow as pa
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    bound_batches(docs.sparkSession)
    extra = T.StructType.fromDDL(added)
    n = 1 + len(also)
    rows = docs.select(F.col("text"), *[F.col(f"`{c}`") for c in (*also, *keep)]).toDF(*[f"c{i}" for i in range(n + len(keep))])
    schema = T.StructType([*[T.StructField(c, f.dataType) for c, f in zip(keep, rows.schema.fields[n:], strict=True)], *extra.fields])
    arrow = to_arrow_schema(extra)

    def run(batches):
        work = make()
        for batch in batches:
            texts = batch.column(0).cast(pa.large_binary())
            for at, end in text_slices(texts, slice_bytes):
                part = batch.slice(at, end - at)
                made = work(texts[at:end].to_pylist(), *[part.column(i).to_pylist() for i in range(1, n)])
                yield pa.RecordBatch.from_arrays([*part.columns[n:], *[pa.array(v, f.type) for v, f in zip(made, arrow, strict=True)]], names=schema.fieldNames())

    return rows.mapInArrow(tidy(run), schema)
