"""The queries opN_<name> and `pipeline`, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from innersearch.llm.common import table


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_pii_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.pii import pii_digest

    return pii_digest(table(spark, sf_dir, "documents"))


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.chat import chat_digest, with_probe

    return chat_digest(with_probe(table(spark, sf_dir, "conversations")))


def op3_language_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.langid import language_digest

    return language_digest(table(spark, sf_dir, "documents"))


def op4_token_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.tokenids import token_digest

    return token_digest(spark, table(spark, sf_dir, "documents"), tokenizer_path())


def op5_suffix_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.decontam import hit_digest

    return hit_digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_signature_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.sigtree import similar_components

    return similar_components(table(spark, sf_dir, "documents"))


def op7_line_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.linededup import copy_digest

    return copy_digest(table(spark, sf_dir, "documents"))


def op8_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.linefilter import line_digest

    return line_digest(table(spark, sf_dir, "documents"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.mixing import mix_digest

    return mix_digest(table(spark, sf_dir, "documents"))


def op10_ring_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from innersearch.llm.ringshard import law_digest

    return law_digest(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {k: v for k, v in globals().items() if k.startswith("op") and k[2].isdigit()}
    return found | {"pipeline": pipeline}


def oracle_sql() -> dict[str, str]:
    from innersearch.llm import chat, decontam, linefilter, oracles, sigtree

    return {
        "op2_chat_format": chat.CHAT_SQL,
        "op5_suffix_decontam": oracles.decontam_sql(decontam.WINDOW),
        "op6_signature_join": oracles.similar_sql(sigtree.WORDS, sigtree.NUM, sigtree.DEN),
        "op8_line_quality": oracles.quality_sql(linefilter.MIN_WORDS, linefilter.MAX_REPEAT, linefilter.OPEN_WORDS, linefilter.MAX_LOST, linefilter.BOILERPLATE),
    }
