"""SQL fragments (DuckDB) with the meaning of the portable operators, written from their definitions: the other side of the
comparison in ``oracle_sql``."""

from __future__ import annotations

from headcount.functions.hashing import coefficients
from headcount.functions.shingles import PRIME


def token(x: str) -> str:
    return f"(('0x' || substr(md5({x}), 1, 8))::BIGINT % {PRIME})"


def hash32(*parts: str) -> str:
    joined = "concat_ws(',', " + ", ".join(f"({p})::VARCHAR" for p in parts) + ")"
    return f"('0x' || substr(md5({joined}), 1, 8))::BIGINT"


def norm(x: str) -> str:
    return f"regexp_replace(lower(coalesce({x}, '')), '[^\\p{{L}}\\p{{N}}]', '', 'g')"


def grams(s: str, k: int) -> str:
    return f"(CASE WHEN length({s}) = 0 THEN []::VARCHAR[] WHEN length({s}) < {k} THEN [{s}] ELSE list_distinct(list_transform(range(1, length({s}) - {k} + 2), lambda i: substring({s}, i, {k}))) END)"


def numbers(g: str) -> str:
    return f"list_distinct(list_transform({g}, lambda g: {token('g')}))"


def sets(source: str, rec_id: str, text: str, k: int, keep: str = "") -> str:
    """CTEs ending in ``sets(rec_id, tokens, ...)``."""
    more = f", {keep}" if keep else ""
    return f"texts AS (SELECT {rec_id} AS rec_id, {norm(text)} AS s{more} FROM {source}), sets AS (SELECT * EXCLUDE (s), {numbers(grams('s', k))} AS tokens FROM texts)"


def minhash(tokens: str, b: int, seed: int = 42) -> str:
    cs = ", ".join(f"{{'a': {a}::BIGINT, 'b': {c}::BIGINT}}" for a, c in coefficients(seed, b))
    return f"list_transform([{cs}], lambda c: list_min(list_transform({tokens}, lambda x: (c.a * x + c.b) % {PRIME})))"


def keys(sig: str, k: int, tables: int) -> str:
    e = "(t + 1)"
    for i in range(k):
        e = f"(({e} * 1000003 + {sig}[t * {k} + {i + 1}]) % {PRIME})"
    return f"list_transform(range(0, {tables}), lambda t: {e})"


def sampled(k: int, tables: int, seed: int = 42) -> str:
    """CTEs from ``sets`` to ``buckets(rec_id, tbl, key)`` and ``pairs(id_a, id_b)``."""
    return (
        f"sigs AS MATERIALIZED (SELECT rec_id, {minhash('tokens', k * tables, seed)} AS sig FROM sets WHERE len(tokens) > 0), "
        f"buckets AS MATERIALIZED (SELECT rec_id, unnest({keys('sig', k, tables)}) AS key, unnest(range(0, {tables})) AS tbl FROM sigs), "
        "pairs AS MATERIALIZED (SELECT DISTINCT x.rec_id AS id_a, y.rec_id AS id_b FROM buckets x JOIN buckets y ON x.tbl = y.tbl AND x.key = y.key AND x.rec_id < y.rec_id)"
    )


def jaccard(a: str, b: str) -> str:
    n = f"len(list_intersect({a}, {b}))"
    return f"(CASE WHEN len({a}) + len({b}) = 0 THEN 1.0 ELSE {n}::DOUBLE / (len({a}) + len({b}) - {n}) END)"


def components(edges: str) -> str:
    """CTEs (to follow WITH RECURSIVE) ending in ``comps(rec_id, component)``."""
    return (
        f"sym AS (SELECT id_a AS a, id_b AS b FROM {edges} UNION SELECT id_b, id_a FROM {edges}), "
        "reach(x, y) AS (SELECT a, b FROM sym UNION SELECT r.x, s.b FROM reach r JOIN sym s ON r.y = s.a), "
        "comps AS (SELECT x AS rec_id, least(x, min(y)) AS component FROM reach GROUP BY x)"
    )


def histogram(n_records: str) -> str:
    """CTE ``hist(size, n)`` from ``comps``; singletons by subtraction from a scalar subquery."""
    return (
        "sizes AS (SELECT component, count(*) AS size FROM comps GROUP BY component), "
        f"hist AS (SELECT size, sum(n)::BIGINT AS n FROM (SELECT size, count(*) AS n FROM sizes GROUP BY size UNION ALL SELECT 1, {n_records} - (SELECT count(*) FROM comps)) GROUP BY size HAVING sum(n) > 0)"
    )


COUNTS = "coalesce(sum(n) FILTER (size = 1), 0)::BIGINT AS s1, coalesce(sum(n) FILTER (size = 2), 0)::BIGINT AS s2, coalesce(sum(n) FILTER (size = 3), 0)::BIGINT AS s3, coalesce(sum(n) FILTER (size > 3), 0)::BIGINT AS s_rest, sum(n)::BIGINT AS observed"


def estimates(rows: str, keep: str, digits: int = 6) -> str:
    """SELECT of the estimate and its errors from rows with p, s1, s2, s3, s_rest."""
    q = "(1 - p)"
    inner = f"SELECT *, s3 / (p * p * (3 - 2 * p)) AS n3 FROM {rows}"
    second = f"SELECT *, (s2 - 3 * p * {q} * {q} * n3) / p AS n2, s1 + s2 * (2 * p - 1) / p + s3 * (1 - 6 * p * {q} * {q}) / (p * p * (3 - 2 * p)) + s_rest AS estimate FROM ({inner})"
    third = f"SELECT *, greatest(n3, 0) * {q} * {q} * (3 * p * p - p + 1) / (p * p * (3 - 2 * p)) + greatest(n2, 0) * {q} / p AS variance FROM ({second})"
    r = lambda e, name: f"round({e}, {digits}) AS {name}"
    status = "CASE WHEN p IS NULL OR p <= 0 THEN 'undefined' WHEN p < 0.5 THEN 'low_p' WHEN n2 < 0 OR n3 < 0 THEN 'negative_counts' ELSE 'ok' END AS status"
    return f"SELECT {keep}{', ' if keep else ''}{r('p', 'p')}, s1, s2, s3, s_rest, observed, {r('n2', 'n2')}, {r('n3', 'n3')}, {r('estimate', 'estimate')}, {r('variance', 'variance')}, {r('sqrt(variance)', 'sd')}, {status} FROM ({third})"


def total_errors(rows: str, digits: int = 6) -> str:
    """The same with the part of the error that comes from p, from rows that also have n_labelled and hits."""
    at = lambda p: f"(s2 * (2 * ({p}) - 1) / ({p}) + s3 * (1 - 6 * ({p}) * (1 - ({p})) * (1 - ({p}))) / (({p}) * ({p}) * (3 - 2 * ({p}))))"
    shrunk = "((hits + 0.5) / (n_labelled + 1))"
    base = estimates(rows, "n_labelled, hits", 30)
    one = f"SELECT *, abs({at('p + 1e-5')} - {at('p - 1e-5')}) / 2e-5 * sqrt({shrunk} * (1 - {shrunk}) / n_labelled) AS sd_p FROM ({base})"
    two = f"SELECT *, sqrt(variance + sd_p * sd_p) AS sd_total FROM ({one})"
    cols = ", ".join(f"round({c}, {digits}) AS {c}" for c in ("p", "n2", "n3", "estimate", "variance", "sd", "sd_p", "sd_total"))
    bounds = f"round(estimate - 1.96 * sd_total, {digits}) AS lo, round(estimate + 1.96 * sd_total, {digits}) AS hi"
    return f"SELECT {cols}, {bounds}, s1, s2, s3, s_rest, observed, status, n_labelled, hits FROM ({two})"


#: The registry fixture (V1) from its definition.
_L = lambda salt: f"translate(md5(concat_ws(',', c_custkey::VARCHAR, '{salt}')), '0123456789', 'ghijklmnop')"
_COPIES = "CASE WHEN c_custkey % 10 <= 5 THEN 1 WHEN c_custkey % 10 <= 8 THEN 2 ELSE 3 END"
REGISTRY = f"""
reg0 AS (SELECT *, unnest(range(0, {_COPIES})) AS copy FROM customer JOIN nation ON c_nationkey = n_nationkey),
reg1 AS (SELECT *, {hash32('c_custkey', 'copy')} AS h, substr({_L('a')}, 1, 7) || ' ' || substr({_L('b')}, 1, 9) AS nm,
  ({hash32('c_custkey', "'no'")} % 200)::VARCHAR || ' ' || substr({_L('s')}, 1, 10) AS st, substr({_L('t')}, 1, 6) || lower(n_name) AS ct FROM reg0),
reg2 AS (SELECT *, CASE WHEN copy = 0 THEN -1 ELSE h % 5 END AS edit, ((h // 5) % 6 + 2)::INT AS pos FROM reg1),
registry AS (SELECT (c_custkey * 4 + copy)::BIGINT AS rec_id, c_custkey AS entity_id, copy::INT AS copy,
  CASE edit WHEN 0 THEN substr(nm, 1, pos) || substr(nm, pos + 2, 40) WHEN 1 THEN substr(nm, 1, pos) || 'x' || substr(nm, pos + 2, 40) ELSE nm END AS full_name,
  CASE WHEN edit = 2 THEN NULL ELSE st END AS street, CASE WHEN edit = 3 THEN substr(ct, 1, 5) ELSE ct END AS city, c_mktsegment AS segment,
  CASE WHEN edit = 4 THEN NULL ELSE round(c_acctbal)::BIGINT::VARCHAR END AS balance, n_regionkey::INT AS region,
  ({hash32('c_custkey', "'day'")} % 700 + CASE WHEN edit = 4 THEN 1 ELSE 0 END)::INT AS event_day FROM reg2)""".strip()
REGISTRY_TEXT = "concat_ws(' ', full_name, street, city, segment, balance)"
