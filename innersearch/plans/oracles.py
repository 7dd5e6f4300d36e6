"""DuckDB SQL for the catalogue: common table expressions with the constants of the plan as literals."""

from __future__ import annotations

from innersearch.functions import chisq
from innersearch.operators.projection import gaussian_matrix

K, C, P, M, SEED, D = 10, 0.9, 0.5, 4, 42, 64
CHI = chisq.quantile(M, P)
MATRIX = gaussian_matrix(M, D, SEED)


def lst(values) -> str:
    return "[" + ", ".join(f"{float(x)!r}::DOUBLE" for x in values) + "]"


def project(v: str, matrix=MATRIX) -> str:
    return "[" + ", ".join(f"list_dot_product({v}, {lst(row)})" for row in matrix) + "]"


SOURCES = {
    "unit": "SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings",
    "skewed": "SELECT vec_id, list_transform(embedding::DOUBLE[], lambda x: x * (1.0::DOUBLE / (1 + ((vec_id * 7919) % 97) / 16.0::DOUBLE))) AS v FROM embeddings",
    "clustered": """SELECT e.vec_id, list_transform(list_zip(c.v, e.embedding::DOUBLE[]), lambda t: (t[1] + 0.35::DOUBLE * t[2]) * (1.0::DOUBLE / (1 + ((e.vec_id * 7919) % 97) / 48.0::DOUBLE))) AS v
      FROM embeddings e JOIN (SELECT label, arg_min(embedding::DOUBLE[], vec_id) AS v FROM embeddings GROUP BY label) c USING (label)""",
}


def base(source: str = "unit", nq: int = 20) -> str:
    return f"""WITH p0 AS ({SOURCES[source]}),
p AS MATERIALIZED (SELECT vec_id, v, list_dot_product(v, v) AS n2, list_sum(list_transform(v, lambda x: abs(x))) AS n1, {project('v')} AS pv FROM p0),
q AS MATERIALIZED (SELECT vec_id AS qid, v AS qv, n2 AS qn2, n1 AS qn1, pv AS qpv FROM p ORDER BY md5(CAST(vec_id AS VARCHAR) || ':{SEED}'), vec_id LIMIT {nq}),
mx AS (SELECT max(n2) AS maxn2 FROM p),
pr AS MATERIALIZED (SELECT qid, vec_id, qn2, round(list_distance(pv, qpv), 9) AS pdist, list_dot_product(v, qv) AS ip FROM p, q WHERE vec_id <> qid),
ex AS MATERIALIZED (SELECT qid, CAST(rn AS INTEGER) AS rank, vec_id, ip FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY ip DESC, vec_id) AS rn FROM pr) WHERE rn <= 100)"""


def margin(best: str) -> str:
    return f"(maxn2 + qn2 - 2 * {best} / {C})"


def steps_k1() -> str:
    """Steps with the running best and both rules, stops, and the answers of the prefix."""
    return f""",
st AS (SELECT *, row_number() OVER w AS rn, max(ip) OVER (PARTITION BY qid ORDER BY pdist, vec_id ROWS UNBOUNDED PRECEDING) AS best FROM pr, mx WINDOW w AS (PARTITION BY qid ORDER BY pdist, vec_id)),
ru AS (SELECT *, {margin('best')} <= 0 AS a, {margin('best')} > 0 AND pdist * pdist >= {CHI!r} * {margin('best')} AS b FROM st),
so AS (SELECT qid, coalesce(min(rn) FILTER (WHERE a OR b), max(rn)) AS stop FROM ru GROUP BY qid),
sr AS (SELECT s.qid, s.stop, CASE WHEN r.a THEN 'A' WHEN r.b THEN 'B' ELSE 'exhausted' END AS reason FROM so s JOIN ru r ON r.qid = s.qid AND r.rn = s.stop)"""


def cells() -> str:
    code = " + ".join(f"CASE WHEN pv[{i + 1}] >= 0 THEN {1 << i} ELSE 0 END" for i in range(M))
    qcode = code.replace("pv[", "qpv[")
    lb = " + ".join(f"CASE WHEN (xor(code, qcode) >> {i}) & 1 = 1 THEN abs(qpv[{i + 1}]) ELSE 0 END" for i in range(M))
    return f""",
co AS MATERIALIZED (SELECT *, CAST({code} AS BIGINT) AS code FROM p),
ce AS (SELECT code, arg_min(vec_id, (n1, vec_id)) AS head_id, min(n1) AS head_n1, arg_min(pv, (n1, vec_id)) AS head_pv, count(*) AS cnt FROM co GROUP BY code),
qc AS (SELECT *, CAST({qcode} AS BIGINT) AS qcode FROM q),
pb AS (SELECT qid, code, head_id, round(list_distance(head_pv, qpv), 9) AS r, round(({lb}) / sqrt({float(M)}), 9) AS lb, head_n1 + qn1 AS ub FROM qc, ce),
pv2 AS (SELECT *, round(lb * lb / ({C} * ub * ub), 9) AS value, row_number() OVER (PARTITION BY qid ORDER BY lb, code) AS rn FROM pb),
pa AS (SELECT qid, coalesce(arg_min(head_id, rn) FILTER (WHERE value >= {CHI!r}), arg_max(head_id, (value, lb, code))) AS anchor_id,
  coalesce(arg_min(r, rn) FILTER (WHERE value >= {CHI!r}), arg_max(r, (value, lb, code))) AS radius, count(*) FILTER (WHERE value >= {CHI!r}) > 0 AS test_passed,
  CAST(coalesce(min(rn) FILTER (WHERE value >= {CHI!r}), max(rn)) AS INTEGER) AS cells_scanned FROM pv2 GROUP BY qid)"""


def ball() -> str:
    """First pass, certificates, enlargement, and final answers."""
    return (
        cells()
        + f""",
kn AS (SELECT qid, max(pdist) AS wide FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY pdist, vec_id) AS rn FROM pr) WHERE rn <= {K} GROUP BY qid),
r1 AS (SELECT qid, CASE WHEN (SELECT count(*) FROM pr WHERE pr.qid = pa.qid AND pdist <= radius) < {K} THEN greatest(radius, wide) ELSE radius END AS radius, radius AS radius0 FROM pa JOIN kn USING (qid)),
f1 AS (SELECT pr.*, radius FROM pr JOIN r1 USING (qid) WHERE pdist <= radius),
k1 AS (SELECT qid, any_value(radius) AS radius, any_value(qn2) AS qn2, count(*) AS n1st, list_sort(list(ip), 'DESC')[{K}] AS kth FROM f1 GROUP BY qid),
c1 AS (SELECT *, {margin('kth')} <= 0 AS cert_a, {margin('kth')} > 0 AND radius * radius >= {CHI!r} * {margin('kth')} AS cert_b,
  greatest(radius, round(sqrt({CHI!r} * greatest(0.0, {margin('kth')})), 9)) AS radius_next FROM k1, mx),
fin AS (SELECT *, CASE WHEN cert_a OR cert_b THEN radius ELSE radius_next END AS radius_final, CASE WHEN cert_a THEN 'A' WHEN cert_b THEN 'B' ELSE 'extended' END AS stop_reason FROM c1),
hit AS MATERIALIZED (SELECT qid, CAST(rn AS INTEGER) AS rank, vec_id, ip FROM (SELECT pr.*, row_number() OVER (PARTITION BY qid ORDER BY ip DESC, vec_id) AS rn FROM pr JOIN fin USING (qid) WHERE pdist <= radius_final) WHERE rn <= {K})"""
    )


def keys(n_key: int = 8) -> str:
    """Clusters around the first vector of labels 0 to 4, ring width, and keys."""
    return f""",
cc AS MATERIALIZED (SELECT CAST(label AS INTEGER) AS part, arg_min(p.pv, p.vec_id) AS c FROM embeddings e JOIN p USING (vec_id) WHERE label < 5 GROUP BY label),
dd AS MATERIALIZED (SELECT p.vec_id, p.pv, cc.part, round(list_distance(p.pv, cc.c), 9) AS d FROM p, cc),
asg AS MATERIALIZED (SELECT vec_id, any_value(pv) AS pv, arg_min(part, (d, part)) AS part, min(d) AS cdist FROM dd GROUP BY vec_id),
pt AS (SELECT part, max(cdist) AS radius, count(*) AS cnt FROM asg GROUP BY part),
ep AS (SELECT round(avg(radius) / {n_key}, 9) AS eps, max(radius) AS rmax FROM pt),
ky AS (SELECT vec_id, part, cdist, CAST(part AS BIGINT) * (CAST(trunc(rmax / eps) AS BIGINT) + 2) + CAST(floor(cdist / eps) AS BIGINT) AS ikey FROM asg, ep)"""
