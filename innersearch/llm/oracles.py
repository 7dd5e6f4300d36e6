"""DuckDB SQL of the operators' queries on the tables `documents` and `benchmark`."""

from __future__ import annotations

import string

SPACE = r"\x20\x09-\x0D"
LOWER = f"translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}')"
#: Words between white space, as they are and with A-Z lowered; words of letters, digits and anything beyond ASCII.
PLAIN = f"regexp_extract_all(coalesce(text, ''), '[^{SPACE}]+')"
SPACED = f"regexp_extract_all({LOWER}, '[^{SPACE}]+')"
ALNUM = rf"regexp_extract_all({LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


def decontam_sql(window: int) -> str:
    """Windows of the items are looked up among the runs of as many words of each document."""
    return f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, {ALNUM} AS w FROM documents),
b AS (SELECT coalesce(CAST(item_id AS VARCHAR), '') AS item_id, {ALNUM} AS w FROM benchmark),
b1 AS (SELECT item_id, w, least({window}, len(w)) AS m FROM b WHERE len(w) > 0),
b2 AS (SELECT item_id, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM b1),
bw AS MATERIALIZED (SELECT DISTINCT item_id, m, array_to_string(w[i:i + m - 1], ' ') AS win FROM b2),
d1 AS (SELECT rid, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM d, (SELECT DISTINCT m FROM bw) WHERE len(w) >= m),
dw AS (SELECT rid, m, i, array_to_string(w[i:i + m - 1], ' ') AS win FROM d1),
hit AS MATERIALIZED (SELECT rid, i, m, item_id FROM dw JOIN bw USING (m, win)),
cov AS (SELECT rid, count(DISTINCT pos) AS n_hit FROM (SELECT rid, unnest(range(i, i + m)) AS pos FROM hit) GROUP BY rid),
its AS (SELECT rid, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT rid, item_id FROM hit) GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN cov USING (rid) LEFT JOIN its USING (rid)"""


def similar_sql(words: int, num: int, den: int) -> str:
    """Pairs by the shingles they share, and the least id reached over them."""
    return f"""WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, {SPACED} AS w FROM documents),
w1 AS (SELECT doc_id, w, least({words}, len(w)) AS m FROM d WHERE len(w) > 0),
w2 AS (SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM w1),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[i:i + m - 1], ' ') AS x FROM w2),
sz AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
both_ AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM sh a JOIN sh b USING (x) WHERE a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
ln AS (SELECT a, b FROM both_ JOIN sz s ON s.doc_id = a JOIN sz t ON t.doc_id = b WHERE {den} * c >= {num} * (s.n + t.n - c)),
ed AS MATERIALIZED (SELECT a, b FROM ln UNION ALL SELECT b, a FROM ln),
re AS (SELECT doc_id AS id, doc_id AS hop FROM d UNION SELECT re.id, ed.b FROM re JOIN ed ON re.hop = ed.a)
SELECT id AS doc_id, coalesce(any_value(n), 0) AS n_shingles, min(hop) AS component_id FROM re LEFT JOIN sz ON sz.doc_id = id GROUP BY id"""


def quality_sql(min_words: int, max_repeat: int, open_words: int, max_lost: float, boilerplate: str) -> str:
    """Measures of the whole text, and the line rules one line a row."""
    white = r"[ \t\n\x0B\f\r]"
    n_in = lambda text, pattern: f"len(regexp_extract_all({text}, '{pattern}'))"
    return f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text, {PLAIN} AS w FROM documents),
t1 AS (SELECT rid, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3),
t2 AS (SELECT rid, i, array_to_string(w[i:i + 2], ' ') AS x FROM t1),
t3 AS (SELECT rid, i, count(*) OVER (PARTITION BY rid, x) AS n FROM t2),
rep AS (SELECT rid, count(DISTINCT pos) AS n_repeat_words FROM (SELECT rid, unnest(range(i, i + 3)) AS pos FROM t3 WHERE n > 1) GROUP BY rid),
l1 AS (SELECT rid, string_split(text, chr(10)) AS ls FROM d),
l2 AS (SELECT rid, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS i, len(ls) AS n_lines FROM l1),
l3 AS (SELECT *, {n_in('line', f'[^{SPACE}]+')} AS words FROM l2),
l4 AS (SELECT *, words = 0 OR ((regexp_matches(regexp_replace(line, '[{SPACE}]+$', ''), '[\\p{{P}}\\p{{S}}]$') OR i = n_lines OR words < {open_words})
  AND NOT (words > 1 AND {n_in('line', f'{white}[|»›•·]{white}')} * 3 >= words) AND NOT {n_in('line', '[#*$%&|<>]')} * 2 > words AND NOT regexp_matches(line, '{boilerplate}')) AS stays FROM l3),
lt AS (SELECT rid, count(*) FILTER (WHERE words > 0) - count(DISTINCT line) FILTER (WHERE words > 0) AS n_dup_lines, CAST(coalesce(sum(words) FILTER (WHERE stays), 0) AS BIGINT) AS words_left FROM l4 GROUP BY rid),
al AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST({n_in('text', '[#*$%&|<>]')} AS BIGINT) AS n_symbols, n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, words_left
  FROM d JOIN lt USING (rid) LEFT JOIN rep USING (rid)),
fa AS (SELECT *, n_words < {min_words} OR 100 * n_repeat_words > {max_repeat} * n_words AS base_failed FROM al)
SELECT *, NOT base_failed AND words_left >= {1 - max_lost} * n_words AS kept FROM fa"""
