"""The corpus pipeline: language ID, near duplicates, decontamination, mixing, token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as
the docs of the next.  All but the last return the columns of documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from innersearch.llm import decontam, langid, mixing, sigtree, tokenids
from innersearch.llm.common import materialize, table
from innersearch.llm.registry import tokenizer_path


#: Least cosines of short and long texts, from the held-out labelled rows of sf0.1 (trained on the others): 3,351 of 3,358
#: stay, and gibberish, code, base64 and other scripts reach 0.172 at most.
LEAST, LEAST_LONG = 0.2, 0.3


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter or unlike every language learned from the labelled documents."""
    return langid.keep_languages(docs, langid.train(docs), least=LEAST, least_long=LEAST_LONG)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document stays of each group of texts whose shingle sets are linked (five words, 0.8)."""
    return sigtree.keep_one(docs, words=5, num=80, den=100)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts spans of benchmark items out of the texts; drops documents that are mostly such spans."""
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of the sources: a row for each time a document is taken."""
    return mixing.mixed_rows(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Writes the ids of the texts in planes, and returns their places read back from the files."""
    return tokenids.token_digest(spark, docs, tokenizer_path())


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("mixture", mixture), ("token_ids", token_ids)]

#: Trained profiles, components and token ids are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage_{name}")
    return docs
