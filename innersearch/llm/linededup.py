"""Deleting later copies of repeated line runs by a suffix array over line ids (Spark expressions only).

Lines with a word are the letters of one long string, documents its pieces.  Suffixes that start with a line
found once are unique and leave at once.  The others are ranked by prefix doubling: the rank of a suffix
for 2^k lines is its first place in the suffix array sorted by those lines, and the pair (rank, rank 2^k lines
on) gives the rank for 2^(k+1) - an aggregation of pairs, a running sum within each old rank, and a join.
Suffixes of one rank form a longest-common-prefix interval of at least 2^k lines; a run of m lines between
powers is the pair of ranks of its first and its last 2^k lines, so every interval is known by two ranks.

A maximal repeated run with at least `min_words` words is the union of its shortest windows of that many words that
begin, or end, at each of its lines.  So the windows are looked up as intervals; every window but the first
of its interval (by doc_id and line) is a later copy, and its lines are deleted.

Defined cases: null and empty texts have no lines; lines are compared without white space at their ends; lines without
words neither break a run nor count and are deleted if they lie inside a deleted run; rows with equal doc_id and
text are one document (all of them get its result); null doc_id sorts first; an empty table gives no rows; other
columns are ignored by the digest and kept by `drop_copies`, whatever their names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from innersearch.llm.common import SPACES, WORD, columns_of, fresh, materialize, text_or_empty

MIN_WORDS = 50
_KEY = ("doc_id", "th")


def line_table(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), lines: array of (ln, h1, h2, words) of lines with a word."""
    text = text_or_empty()
    bare = lambda line: F.btrim(line, F.lit(SPACES))
    lines = F.filter(F.transform(F.split(text, "\n"), lambda line, i: F.struct(i.alias("ln"), bare(line).alias("line"))), lambda x: x["line"] != "")
    shown = F.transform(
        lines, lambda x: F.struct(x["ln"].alias("ln"), F.xxhash64(x["line"]).alias("h1"), F.xxhash64(F.lit("#"), x["line"]).alias("h2"), F.regexp_count(x["line"], F.lit(WORD)).alias("words"))
    )
    return docs.select("doc_id", F.xxhash64(text).alias("th"), shown.alias("lines"))


def first_ranks(letters: DataFrame) -> DataFrame:
    """h1, h2, r0 of the line ids found at least twice: the places of their suffixes in the array."""
    found = materialize(letters.groupBy("h1", "h2").agg(F.count("*").alias("n")).where("n > 1").withColumn("cell", F.shiftright("h1", 52)), "line_ids")
    cells = found.groupBy("cell").agg(F.sum("n").alias("total"))  # at most 4096
    base = cells.select(F.col("cell").alias("b_cell"), F.coalesce(F.sum("total").over(Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("cell").orderBy("h1", "h2").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return found.withColumn("inside", inside).join(F.broadcast(base), F.col("cell") == F.col("b_cell")).select(F.col("h1").alias("p1"), F.col("h2").alias("p2"), (F.col("base") + F.col("inside")).alias("r0"))


def _reach(part: Column, min_words: int, step: int) -> Column:
    """Lines of the shortest window of min_words words from the first element of part on (step 1) or back (-1)."""
    start = F.struct(F.lit(0).alias("words"), F.lit(0).alias("m"), part[0]["idx"].alias("at"), F.lit(True).alias("on"))

    def add(a: Column, x: Column) -> Column:
        on = a["on"] & (a["words"] < min_words) & (x["idx"] == a["at"])
        return F.struct(
            F.when(on, a["words"] + x["words"]).otherwise(a["words"]).alias("words"), F.when(on, a["m"] + 1).otherwise(a["m"]).alias("m"), F.when(on, a["at"] + step).otherwise(a["at"]).alias("at"), (a["on"] & (on | (a["words"] >= min_words))).alias("on")
        )

    return F.aggregate(part, start, add, lambda a: F.when(a["words"] >= min_words, a["m"]))


def ranked(lines: DataFrame, min_words: int) -> tuple[DataFrame, int]:
    """Rows (doc_id, th, idx, ln, mf, mb, r0..rK) of the lines found at least twice, in documents where a window
    of min_words words of such lines exists; and K."""
    letters = lines.select(*_KEY, F.posexplode("lines").alias("idx", "l")).select(*_KEY, "idx", "l.*")
    met = letters.join(first_ranks(letters), (F.col("h1") == F.col("p1")) & (F.col("h2") == F.col("p2")))
    met = met.groupBy(*_KEY).agg(F.array_distinct(F.sort_array(F.collect_list(F.struct("idx", "ln", "words", "r0")))).alias("a"))
    n = F.lit(min_words)
    with_m = F.transform(
        F.array(F.col("a")),
        lambda a: F.transform(
            a,
            lambda x, i: F.struct(
                x["idx"].alias("idx"), x["ln"].alias("ln"), x["r0"].alias("r0"),
                F.when(x["words"] >= n, F.lit(1)).otherwise(_reach(F.slice(a, i + 1, n), min_words, 1)).alias("mf"),
                F.when(x["words"] >= n, F.lit(1)).otherwise(_reach(F.reverse(F.slice(a, F.greatest(i + 2 - n, F.lit(1)), F.least(n, i + 1))), min_words, -1)).alias("mb"),
            ),
        ),
    )[0]
    met = met.select(*_KEY, with_m.alias("a")).where(F.exists("a", lambda x: x["mf"].isNotNull() | x["mb"].isNotNull()))
    rows = materialize(met.select(*_KEY, F.explode("a").alias("x")).select(*_KEY, "x.*"), "ranks0")
    most = rows.agg(F.max(F.greatest("mf", "mb"))).first()[0] or 1
    top = int(most).bit_length() - 1
    for k in range(top):
        along = Window.partitionBy(*_KEY).orderBy("idx")
        r, nxt = f"r{k}", F.when(F.lead("idx", 2**k).over(along) == F.col("idx") + 2**k, F.lead(f"r{k}", 2**k).over(along))
        rows = materialize(rows.withColumn("next", nxt), f"pairs{k}")
        pairs = rows.where(f"{r} is not null and next is not null").groupBy(r, "next").agg(F.count("*").alias("n")).where("n > 1")
        before = F.coalesce(F.sum("n").over(Window.partitionBy(r).orderBy("next").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        pairs = pairs.select(F.col(r).alias("q1"), F.col("next").alias("q2"), (F.col(r) + before).alias(f"r{k + 1}"))
        rows = rows.join(pairs, (F.col(r) == F.col("q1")) & (F.col("next") == F.col("q2")), "left").drop("q1", "q2", "next")
    return (materialize(rows, "ranks") if top else rows), top


def later_copies(rows: DataFrame, top: int) -> DataFrame:
    """doc_id, th, copies: array of (first line, last line) of windows that are not the first of their interval."""
    ranks = [f"r{k}" for k in range(top + 1)]
    docs = rows.groupBy(*_KEY).agg(F.sort_array(F.collect_list(F.struct("idx", "ln", "mf", "mb", F.array(*ranks).alias("r")))).alias("a"))

    def windows(a: Column) -> Column:
        def one(i: Column, first: Column, m: Column) -> Column:
            """The window of m lines whose first element has place `first` in a."""
            k = F.floor(F.log2(m) + 1e-9).cast("int")
            span = F.pow(F.lit(2), k).cast("int")
            head, last = F.get(a, first), F.get(a, first + m - 1)
            return F.struct(m.alias("m"), F.get(head["r"], k).alias("q1"), F.get(F.get(a, first + m - span)["r"], k).alias("q2"), head["idx"].alias("at"), head["ln"].alias("from"), last["ln"].alias("to"))

        forward = F.transform(a, lambda x, i: F.when(x["mf"].isNotNull(), one(i, i, x["mf"])))
        back = F.transform(a, lambda x, i: F.when(x["mb"].isNotNull() & (x["mb"] > 1), one(i, i - x["mb"] + 1, x["mb"])))
        return F.filter(F.array_distinct(F.concat(forward, back)), lambda w: w["q1"].isNotNull() & w["q2"].isNotNull())

    found = docs.select(*_KEY, F.explode(F.transform(F.array("a"), windows)[0]).alias("w")).select(*_KEY, "w.*")
    found = materialize(found, "windows")
    firsts = found.groupBy("m", "q1", "q2").agg(F.min(F.struct("doc_id", "at")).alias("first"), F.count("*").alias("n")).where("n > 1")
    firsts = firsts.select(F.col("m").alias("m_"), F.col("q1").alias("q1_"), F.col("q2").alias("q2_"), "first")
    later = found.join(firsts, (F.col("m") == F.col("m_")) & (F.col("q1") == F.col("q1_")) & (F.col("q2") == F.col("q2_"))).where(F.col("first") < F.struct("doc_id", "at"))
    return later.groupBy(*_KEY).agg(F.collect_list(F.struct(F.col("from").alias("from"), F.col("to").alias("to"))).alias("copies"))


def deleted_lines(copies: Column) -> Column:
    """Sorted line numbers inside the ranges."""
    return F.array_sort(F.array_distinct(F.flatten(F.transform(copies, lambda c: F.sequence(c["from"], c["to"])))))


def find_copies(docs: DataFrame, min_words: int = MIN_WORDS) -> tuple[DataFrame, DataFrame]:
    """The line table, and doc_id, th, deleted (line numbers) of documents with later copies."""
    lines = materialize(line_table(docs), "lines")
    rows, top = ranked(lines, min_words)
    return lines, later_copies(rows, top).select(*_KEY, deleted_lines(F.col("copies")).alias("deleted"))


def drop_copies(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """docs without the later copies; a document left without a line with a word is dropped."""
    _, gone = find_copies(docs, min_words)
    g_id, g_th, g_lines, th = (fresh(docs.columns, n) for n in ("id", "th", "lines", "text_hash"))
    gone = gone.select(F.col("doc_id").alias(g_id), F.col("th").alias(g_th), F.col("deleted").alias(g_lines))
    met = docs.withColumn(th, F.xxhash64(text_or_empty())).join(gone, F.col("doc_id").eqNullSafe(F.col(g_id)) & (F.col(th) == F.col(g_th)), "left")
    left = F.array_join(F.filter(F.transform(F.split("text", "\n"), lambda line, i: F.when(~F.array_contains(g_lines, i), line)), lambda x: x.isNotNull()), "\n")
    met = met.withColumn("text", F.when(F.col(g_lines).isNull(), F.col("text")).otherwise(left))
    return met.where(F.col(g_lines).isNull() | F.rlike("text", F.lit(WORD))).select(*columns_of(docs))


def copy_digest(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """doc_id, n_lines (with a word), n_deleted, deleted (comma-joined numbers of all deleted lines) of every row."""
    lines, gone = find_copies(docs.select("doc_id", "text"), min_words)
    gone = gone.select(F.col("doc_id").alias("g_id"), F.col("th").alias("g_th"), "deleted")
    out = lines.select(*_KEY, F.size("lines").cast("long").alias("n_lines"), F.transform("lines", lambda x: x["ln"]).alias("lns"))
    out = out.join(gone, F.col("doc_id").eqNullSafe(F.col("g_id")) & (F.col("th") == F.col("g_th")), "left")
    deleted = F.coalesce("deleted", F.array().cast("array<int>"))
    return out.select("doc_id", "n_lines", F.size(F.array_intersect("lns", deleted)).cast("long").alias("n_deleted"), F.array_join(deleted, ",").alias("deleted"))
