import subprocess
import sys

import __spark_entry__


def test_every_oracle_has_a_query():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_entry_stands_without_the_optional_subpackage():
    code = "import sys; sys.modules['innersearch.llm'] = None; import __spark_entry__ as e; assert e.llm is None and 'exact_topk' in e.queries()"
    subprocess.run([sys.executable, "-c", code], check=True)


def test_flagship(spark):
    df = __spark_entry__.entry(spark)
    assert df.columns == ["qid", "rank", "vec_id", "ip"] and df.count() > 0
