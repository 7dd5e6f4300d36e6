import base64
import random

from pyspark.sql import functions as F

import corpus_pipeline
from innersearch.llm import langid


def test_pipeline(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(120)
    names = docs.columns
    counts = []
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf_dir)
        counts.append(docs.count())
        if name != "token_ids":
            assert docs.columns == names
    assert counts[0] <= 120 and counts[1] <= counts[0] and counts[-1] == counts[-2]


def test_empty(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf_dir)
    assert docs.count() == 0


def test_language_stage_decides(spark):
    """Held-out labelled rows stay; gibberish, code, other scripts and languages not learned go."""
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    r = random.Random(5)
    bad = ["".join(r.choice("abcdefghijklmnopqrstuvwxyz    ") for _ in range(n)) for n in (100, 300, 1000, 5000) for _ in range(10)]
    bad += [base64.b64encode(r.randbytes(n)).decode() for n in (100, 1000) for _ in range(10)]
    bad += ["".join(chr(r.randrange(0x4E00, 0x9FA0)) for _ in range(n)) for n in (100, 1000) for _ in range(10)]
    bad += [f"for (int i = 0; i < n; i++) {{ x[i] = malloc(sizeof(*p)); if (!x[i]) return NULL; }}\nstatic void f_{i}(void) {{}}" for i in range(10)]
    bad += ["Pojedziemy jutro do miasta, \u017ceby kupi\u0107 chleb i mleko dla ca\u0142ej rodziny.", "Menimme eilen kauppaan ostamaan leip\u00e4\u00e4 ja maitoa koko perheelle."]
    held = table.where(langid.held_out() & F.col("lang").isNotNull())
    planted = spark.createDataFrame([(-1 - i, t) for i, t in enumerate(bad)], "doc_id long, text string")
    learned = langid.train(table.where(~langid.held_out()))

    def kept(docs, profiles):
        return langid.keep_languages(docs, profiles, least=corpus_pipeline.LEAST, least_long=corpus_pipeline.LEAST_LONG).count()

    assert kept(held, learned) >= 0.99 * held.count()
    assert kept(planted, learned) == 0
    for lang, most in (("de", 0.1), ("en", 0.1), ("fr", 0.5), ("es", 0.7)):
        rest = langid.train(table.where(~langid.held_out() & (F.col("lang") != lang)))
        one = held.where(F.col("lang") == lang)
        assert kept(one, rest) <= most * one.count()
    # the stage itself, whose profiles also learn from the labelled rows among its input
    names = table.columns
    mixed = table.unionByName(planted, allowMissingColumns=True).select(*names)
    gone = mixed.select("doc_id").exceptAll(corpus_pipeline.language(spark, mixed, "").select("doc_id"))
    assert gone.where("doc_id < 0").count() == len(bad)
    assert gone.where("doc_id >= 0").count() <= 0.01 * table.count()


def test_language_stage_equals_brute_force(spark, sf_dir):
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    profiles = langid.train(table)
    want = []
    for i, text in sorted((r["doc_id"], r["text"]) for r in table.select("doc_id", "text").collect()):
        g = langid.grams_of(text or "")
        if len(g):
            v = langid.gram_vectors(g, profiles.letters).astype(float).sum(0)
            n = langid.gram_counts(text)[1]
            cos = max(p @ v / (p @ p) ** 0.5 for p in profiles.vectors) / (profiles.dim * float(n @ n)) ** 0.5
            if cos >= (corpus_pipeline.LEAST_LONG if len(text) >= langid.LONG_CHARS else corpus_pipeline.LEAST):
                want.append(i)
    assert sorted(r["doc_id"] for r in corpus_pipeline.language(spark, table, sf_dir).select("doc_id").collect()) == want
