"""The queries with SQL against DuckDB, on a given table and on rows of the defined cases."""

import pytest

import __spark_entry__ as entry
from tests.compare import TABLES, oracle_rows, rows_of

NAMES = ("op2_chat_format", "op5_suffix_decontam", "op6_signature_join", "op8_line_quality")
LONG = "eins zwei drei vier fünf sechs sieben acht neun zehn elf zwölf"
TEXTS = [
    None, "", " \n\t ", "a", "A b", LONG, LONG.upper(), f"x {LONG}, y", f"{LONG} {LONG}", "ja " * 3000,
    "Home | News | About\nplain words that close without any point at all here\nEnd.\r\n\nClick here now.\n# # # a\nEnd.\r",
    "\n".join(f"A line of words with number {i} that ends as it should." for i in range(12)), " ".join(f"w{i}" for i in range(80)),
    "\n".join(["One more line that all texts share."] * 20), "日本語 テキスト。\nно это другой язык.  x", "emoji 😀 " * 30,
]
ITEMS = [(1, LONG), (2, "Elf, zwölf"), (10, None), (11, "..."), (12, "w3 w4 w5 w6 w7 w8 w9 w10 w11 w12 w13 w14"), (13, LONG)]


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf_dir, name):
    assert rows_of(entry.queries()[name](spark, sf_dir)) == oracle_rows(entry.oracle_sql()[name], sf_dir)


@pytest.mark.parametrize("name", NAMES[1:])
def test_oracle_on_defined_cases(spark, sf_dir, tmp_path, name):
    import shutil

    for t in TABLES:
        shutil.copy(f"{sf_dir}/{t}.parquet", tmp_path / f"{t}.parquet") if t not in ("documents", "benchmark") else None
    rows = [(i, t, "de", None if i % 3 else "s", None if t is None else len(t)) for i, t in enumerate(TEXTS)]
    put = lambda df, t: df.toPandas().to_parquet(tmp_path / f"{t}.parquet")
    put(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars int"), "documents")
    put(spark.createDataFrame(ITEMS, "item_id long, text string"), "benchmark")
    assert rows_of(entry.queries()[name](spark, str(tmp_path))) == oracle_rows(entry.oracle_sql()[name], str(tmp_path))
