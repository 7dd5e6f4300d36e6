"""Mixing sources to target weights with Efraimidis-Spirakis sampling (DataFrame functions only).

A source whose target is at least its size is first taken whole, epoch by epoch.  The rest of its
target is a weighted sample without replacement: each document draws the key -ln(u) / weight, with u
from a hash of its id and weight its quality, and documents are taken in key order until the words reach
the budget; the document on the boundary is taken up to the budget.

The order is never sorted in one task: keys fall into 4096 bins of their distribution, bin sums give
the bin on the boundary, and only that bin's rows of each source are sorted.

Defined cases: a null text has no words; null is a source of its own, last in order; an empty source name
is a source; keys hash doc_id and text, so rows of one doc_id differ in key and repeated rows are rows of their own with equal
keys; an empty table gives no rows; other columns are kept by `mix`, whatever their names, and ignored by the digest."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from innersearch.llm.common import SPACES, WORD, columns_of, fresh, materialize, text_or_empty

#: Weights of the sources in order, repeating; share of all words; most epochs of a source.
WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2.0
BINS = 4096
#: Sources whose plan may be broadcast (under 100 bytes each).
BROADCAST_SOURCES = 100_000


def n_words(col: Column) -> Column:
    return F.regexp_count(col, F.lit(WORD)).cast("long")


def quality_weight(col: Column) -> Column:
    """Quality from the text alone: 1 less the share of symbol characters, at least 0.1."""
    symbols = F.length(col) - F.length(F.translate(col, "#*$%&|<>{}[]=_~^\\", ""))
    return F.greatest(F.lit(0.1), 1 - 4 * symbols / F.greatest(F.length(col), F.lit(1)))


def targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """source, source_size, target: `share` of all words dealt by weight, none above `most` times its size.

    The level at which the remaining weight is served follows from the sources in order of
    most * size / weight: those below the level stop at their limit, the excess goes to the others."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    s = sizes.select("source", "source_size", w.alias("w")).withColumn("stop", most * F.col("source_size")).withColumn("ratio", F.col("stop") / F.col("w"))
    by_ratio = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    onward = by_ratio.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (share * F.sum("source_size").over(everything) - F.coalesce(F.sum("stop").over(before), F.lit(0.0))) / F.sum("w").over(onward)
    s = s.withColumn("level", level).withColumn("open", F.when(F.col("level") <= F.col("ratio"), F.col("level")))
    s = s.withColumn("level", F.coalesce(F.max("open").over(everything), F.max("ratio").over(everything)))
    return s.select("source", "source_size", F.least("stop", F.col("level") * F.col("w")).alias("target"))


def with_keys(docs: DataFrame, size: Column, weight: Column, salt: Column, seed: int) -> DataFrame:
    """Columns row (struct of all columns of docs), source, and mix: struct(size, key, bin, salt).

    The row is packed, so its columns clash with none made here."""
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("doc_id"), salt), 11).cast("double") + 0.5) / float(2**53)
    key = -F.log(u) / weight
    bin_ = F.least(F.lit(BINS - 1), F.floor(BINS * (1 - F.exp(-key)))).cast("int")
    return docs.select(F.struct(*columns_of(docs)).alias("row"), "source", F.struct(size.alias("size"), key.alias("key"), bin_.alias("bin"), salt.alias("salt")).alias("mix"))


def source_plan(keyed: DataFrame) -> DataFrame:
    """One row a source: source_size, target, whole epochs, boundary bin, words left at its start."""
    bins = keyed.groupBy("source", F.col("mix.bin").alias("bin")).agg(F.sum("mix.size").alias("words"))
    bins = materialize(bins, "mix_bins")
    sizes = bins.groupBy("source").agg(F.sum("words").alias("source_size"))
    plan = targets(sizes).withColumn("epochs", F.coalesce(F.floor(F.try_divide("target", "source_size")), F.lit(0)).cast("long"))
    plan = plan.withColumn("budget", F.round("target").cast("long") - F.col("epochs") * F.col("source_size"))
    running = F.sum("words").over(Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1))
    cum = bins.withColumn("before", F.coalesce(running, F.lit(0))).withColumnRenamed("source", "b_source")
    edge = cum.join(plan, F.col("b_source").eqNullSafe(F.col("source")) & (F.col("before") < F.col("budget")))
    edge = edge.groupBy("b_source").agg(F.max(F.struct("bin", "before")).alias("edge"))
    plan = plan.join(edge, F.col("b_source").eqNullSafe(F.col("source")), "left")
    return materialize(
        plan.select(
            F.col("source").alias("p_source"), "source_size", "target", "epochs", F.coalesce("edge.bin", F.lit(-1)).alias("edge_bin"), (F.col("budget") - F.coalesce("edge.before", F.lit(0))).alias("left")
        ),
        "mix_plan",
    )


def mix(docs: DataFrame, size: Column | None = None, weight: Column | None = None, salt: Column | None = None, seed: int = 17) -> DataFrame:
    """Columns row (struct of all columns of docs(doc_id, text, source, ...)) and take: struct(size, source_size, target, epochs, part):
    the document is taken `epochs` times whole and once up to its first `part` words (0: not)."""
    text = text_or_empty()
    keyed = with_keys(docs, n_words(text) if size is None else size, quality_weight(text) if weight is None else weight, F.xxhash64(text) if salt is None else salt, seed)
    plan = source_plan(keyed)
    plan = F.broadcast(plan) if plan.count() <= BROADCAST_SOURCES else plan
    met = keyed.join(plan, F.col("source").eqNullSafe(F.col("p_source")))

    def take(part: Column) -> list[Column]:
        return [F.col("row"), F.struct(F.col("mix.size").alias("size"), "source_size", "target", "epochs", part.cast("long").alias("part")).alias("take")]

    in_order = Window.partitionBy("p_source").orderBy("mix.key", "row.doc_id", "mix.salt", "mix.size").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("mix.size").over(in_order), F.lit(0))
    edge = met.where(F.col("mix.bin") == F.col("edge_bin")).select(*take(F.greatest(F.lit(0), F.least(F.col("mix.size"), F.col("left") - before))))
    rest = met.where(F.col("mix.bin") != F.col("edge_bin")).select(*take(F.when(F.col("mix.bin") < F.col("edge_bin"), F.col("mix.size")).otherwise(0)))
    return rest.unionByName(edge)


def first_words(text: Column, n: Column) -> Column:
    """text up to the end of its n-th word, n from 1; the white space before that stays as it is."""
    body = F.ltrim(text, F.lit(SPACES))
    parts = F.split(body, r"[\x20\x09-\x0D]+", (n + 1).cast("int"))
    rest = F.when(F.size(parts) > n, F.length(F.get(parts, n.cast("int")))).otherwise(0)
    return F.rtrim(F.left(text, F.length(text) - rest), F.lit(SPACES))


def mixed_rows(docs: DataFrame, seed: int = 17) -> DataFrame:
    """The mix itself, with the columns of docs: one row for each time a document is taken; a
    document on a boundary keeps the text up to the last word that fits."""
    t = F.col("take")
    whole = t["epochs"] + F.when((t["part"] > 0) & (t["part"] == t["size"]), 1).otherwise(0)
    cut = (t["part"] > 0) & (t["part"] < t["size"])
    times = F.flatten(F.array(F.array_repeat(F.lit(-1).cast("long"), whole.cast("int")), F.when(cut, F.array(t["part"])).otherwise(F.array().cast("array<long>"))))
    rows = mix(docs, seed=seed).select("row", F.explode(times).alias("n"))
    text = F.when(F.col("n") < 0, F.col("row")["text"]).otherwise(first_words(F.col("row")["text"], F.col("n")))
    return rows.select(*[text.alias(c) if c == "text" else F.col("row")[c].alias(c) for c in docs.columns])


def mix_digest(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row."""
    text = text_or_empty()
    narrow = materialize(docs.select("doc_id", "source", n_words(text).alias("size"), quality_weight(text).alias("weight"), F.xxhash64(text).alias("salt")), "mix_rows")
    t = F.col("take")
    out = mix(narrow, F.col("size"), F.col("weight"), F.col("salt"))
    return out.select("row.doc_id", t["size"].alias("size"), t["source_size"].alias("source_size"), t["target"].alias("target"), (t["epochs"] * t["size"] + t["part"]).alias("taken"))
