"""Line-first cleaning (Spark expressions only).

Every line is judged by rules - closing punctuation, navigation, boilerplate, symbols - and failing lines
are removed; a document that loses more than half of its words is rejected.  Before that, whole texts that are
short (under 50 words) or repeat themselves (over half of their words in 3-word windows found twice) fail.

Defined cases: null and empty texts have no words and fail; lines are split at \\n, a carriage return at the end
counts as white space; lines without words are kept but count for nothing; repeated rows are rows of their own; an
empty table gives no rows; other columns are ignored by the digest and kept by `clean`, whatever their names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.llm.common import SPACES, columns_of, fresh, text_or_empty

SYMBOLS = "#*$%&|<>"
MIN_WORDS, MAX_REPEAT = 50, 50
#: A line of at least this many words must close with punctuation, unless it is the last one.
OPEN_WORDS = 8
MAX_LOST = 0.5
#: Phrases of boilerplate lines (lower case) and separators of navigation lines.
BOILERPLATE = r"(?i)\b(all rights reserved|licensed under|copyright \(c\)|terms of (use|service)|privacy policy|cookie policy|accept cookies|javascript is disabled|subscribe to our newsletter|click here|spdx-license-identifier)\b|©"
SEPARATORS = r"\s[|»›•·]\s"


def split_words(text: Column) -> Column:
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")


def n_chars_of(text: Column, chars: str) -> Column:
    return F.length(text) - F.length(F.translate(text, chars, ""))


def repeat_words(words: Column) -> Column:
    """Words inside 3-word windows that occur at least twice.

    The windows are sorted with their places; equal neighbours mark their places, and the places in
    order count 3 words each, less what they share with the next."""
    n = F.size(words)
    windows = F.transform(F.sequence(F.lit(1), n - 2), lambda i: F.struct(F.concat_ws(" ", F.get(words, i - 1), F.get(words, i), F.get(words, i + 1)).alias("w"), i.alias("i")))
    s = F.array_sort(windows)

    def marked(s: Column) -> Column:
        same = F.filter(s, lambda x, k: (x["w"] == F.get(s, k - 1)["w"]) | (x["w"] == F.get(s, k + 1)["w"]))
        return F.array_sort(F.transform(same, lambda x: x["i"]))

    step = lambda a, p: F.struct((a["n"] + F.least(F.lit(3), p + 2 - a["to"])).alias("n"), (p + 2).alias("to"))
    covered = F.aggregate(F.transform(F.array(s), marked)[0], F.struct(F.lit(0).alias("n"), F.lit(-9).alias("to")), step, lambda a: a["n"])
    return F.when(n < 4, F.lit(0)).otherwise(covered).cast("long")


def line_kept(line: Column, words: Column, last: Column) -> Column:
    """The verdict of the rules on one line of `words` words."""
    bare = F.rtrim(F.translate(line, SPACES[1:], " "))
    closed = F.rlike(bare, F.lit(r"[\p{P}\p{S}]$"))
    navigation = (words > 1) & (F.regexp_count(line, F.lit(SEPARATORS)) * 3 >= words)
    symbols = n_chars_of(line, SYMBOLS) * 2 > words
    return (words == 0) | ((closed | last | (words < OPEN_WORDS)) & ~navigation & ~symbols & ~F.rlike(line, F.lit(BOILERPLATE)))


def judged_lines(text: Column) -> Column:
    """array<struct<line, words, kept>> of a text."""
    lines = F.split(text, "\n")
    count = lambda line: F.size(split_words(line))
    with_n = F.transform(lines, lambda line: F.struct(line.alias("line"), count(line).alias("words")))
    return F.transform(F.array(with_n), lambda ls: F.transform(ls, lambda x, k: F.struct(x["line"].alias("line"), x["words"].alias("words"), line_kept(x["line"], x["words"], k == F.size(ls) - 1).alias("kept"))))[0]


def measured(docs: DataFrame, name: str) -> DataFrame:
    """docs with the struct `name`: counts, verdicts and the cleaned text."""
    text, words, lines = (fresh([*docs.columns, name], n) for n in ("text", "words", "lines"))
    d = docs.withColumn(text, text_or_empty()).withColumn(words, split_words(F.col(text))).withColumn(lines, judged_lines(F.col(text)))
    full = F.filter(lines, lambda x: x["words"] > 0)
    n = F.size(words).cast("long")
    repeat = repeat_words(F.col(words))
    kept_lines = F.filter(lines, lambda x: x["kept"])
    total = lambda xs: F.aggregate(xs, F.lit(0), lambda a, x: a + x["words"])
    d = d.withColumn(
        name,
        F.struct(
            n.alias("n_words"),
            (F.length(text) - n_chars_of(F.col(text), SPACES)).cast("long").alias("word_chars"),
            n_chars_of(F.col(text), SYMBOLS).cast("long").alias("n_symbols"),
            (F.size(full) - F.size(F.array_distinct(F.transform(full, lambda x: x["line"])))).cast("long").alias("n_dup_lines"),
            repeat.alias("n_repeat_words"),
            F.array_join(F.transform(kept_lines, lambda x: x["line"]), "\n").alias("cleaned"),
            total(kept_lines).cast("long").alias("words_left"),
        ),
    )
    return d.drop(text, words, lines)


def verdicts(x: Column) -> tuple[Column, Column]:
    failed = (x["n_words"] < MIN_WORDS) | (100 * x["n_repeat_words"] > MAX_REPEAT * x["n_words"])
    return failed, ~failed & (x["words_left"] >= (1 - MAX_LOST) * x["n_words"])


def clean(docs: DataFrame) -> DataFrame:
    """docs that pass, their texts without the failing lines.

    The generator keeps the filter above the measures, which would else be computed again for it."""
    line = fresh(docs.columns, "line")
    found = measured(docs, line).withColumn(line, F.explode(F.array(line)))
    return found.where(verdicts(F.col(line))[1]).withColumn("text", F.col(line)["cleaned"]).select(*columns_of(docs))


def line_digest(docs: DataFrame) -> DataFrame:
    x = F.col("line")
    failed, kept = verdicts(x)
    return measured(docs.select("doc_id", "text"), "line").select("doc_id", *[x[c].alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], failed.alias("base_failed"), kept.alias("kept"), x["words_left"].alias("words_left"))
