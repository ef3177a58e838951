"""SQL twins (DuckDB) of the queries that SQL can express, written from the contracts."""

from __future__ import annotations

from .quality_rules import MAX_REPEAT_PERCENT, MIN_WORDS, RULES, STOP_WORDS

_WORD = r"[^\x20\x09-\x0D]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _without(keep: str) -> str:
    return f"length(regexp_replace(t, '[^{keep}]', '', 'g'))::BIGINT"


def _rules() -> str:
    out = []
    for r in RULES:
        if r.low is not None:
            out.append(f"({r.whole} = 0 OR 1000 * {r.part} >= {r.low} * {r.whole})")
        if r.high is not None:
            out.append(f"({r.whole} = 0 OR 1000 * {r.part} <= {r.high} * {r.whole})")
    return " AND ".join(out)


def quality_rules() -> str:
    stops = ", ".join(f"'{w}'" for w in dict.fromkeys(STOP_WORDS))
    failed = f"(n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words)"
    return f"""
WITH w AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS ws,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '{_WORD}')) AS ls FROM documents),
g AS (SELECT doc_id, i, ws[i] || chr(10) || ws[i + 1] || chr(10) || ws[i + 2] AS g FROM w, LATERAL (SELECT unnest(range(1, len(ws) - 1)) AS i)),
r AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM r, (VALUES (0), (1), (2)) v(k) GROUP BY doc_id),
m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars, {_without("#*$%&|<>")} AS n_symbols,
    (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, len(ls)::BIGINT AS n_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words,
    len(list_filter(ws, lambda x: lower(x) IN ({stops})))::BIGINT AS n_stop_words, len(list_filter(ws, lambda x: contains(x, '!!')))::BIGINT AS n_exclamations,
    {_without(chr(92) + "p{L}")} AS n_letters, {_without("A-Z")} AS n_capitals FROM w LEFT JOIN c USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, {failed} AS base_failed, NOT {failed} AND {_rules()} AS kept FROM m"""


def decontamination(window: int = 10) -> str:
    words = f"regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
    return f"""
WITH d AS (SELECT doc_id, {words} AS w FROM documents), b AS (SELECT item_id, {words} AS w FROM benchmark WHERE text IS NOT NULL),
l AS (SELECT DISTINCT least({window}, len(w)) AS n FROM b WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS s FROM (SELECT *, least({window}, len(w)) AS n FROM b WHERE len(w) > 0), LATERAL (SELECT unnest(range(1, len(w) - n + 2)) AS i)),
dw AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS s FROM d, l, LATERAL (SELECT unnest(range(1, len(w) - n + 2)) AS i)),
h AS (SELECT doc_id, item_id, dw.n, i FROM dw JOIN bw ON dw.n = bw.n AND dw.s = bw.s),
p AS (SELECT doc_id, count(DISTINCT i + k)::BIGINT AS n_hit FROM h, LATERAL (SELECT unnest(range(0, n)) AS k) GROUP BY doc_id),
q AS (SELECT doc_id, count(*)::BIGINT AS n_items, string_agg(x, ',' ORDER BY x) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS x FROM h) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN q USING (doc_id)"""


def jaccard(k: int = 5, percent: int = 80) -> str:
    return f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{_WORD}') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + {k - 1}], ' ') AS g FROM w, LATERAL (SELECT unnest(CASE WHEN len(w) = 0 THEN []::BIGINT[] WHEN len(w) < {k} THEN [1] ELSE range(1, len(w) - {k - 2}) END) AS i)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {percent} * (x.n + y.n - c)),
sym AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
r(x, y) AS (SELECT a, b FROM sym UNION SELECT r.x, sym.b FROM r JOIN sym ON r.y = sym.a),
k AS (SELECT x AS doc_id, least(x, min(y)) AS component_id FROM r GROUP BY x)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(k.component_id, w.doc_id) AS component_id FROM w LEFT JOIN n USING (doc_id) LEFT JOIN k USING (doc_id)"""


def substrings(window: int = 50) -> str:
    return f"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS w FROM documents),
v AS (SELECT doc_id, i, md5(array_to_string(w[i:i + {window - 1}], ' ')) AS h FROM w, LATERAL (SELECT unnest(range(1, len(w) - {window - 2})) AS i)),
f AS (SELECT doc_id, i FROM v QUALIFY min(doc_id) OVER (PARTITION BY h) < doc_id),
g AS (SELECT doc_id, list(DISTINCT i + k) AS gone FROM f, LATERAL (SELECT unnest(range(0, {window})) AS k) GROUP BY doc_id),
p AS (SELECT w.doc_id, i, w[i] AS x FROM w JOIN g USING (doc_id), LATERAL (SELECT unnest(range(1, len(w) + 1)) AS i)),
t AS (SELECT p.doc_id, string_agg(x, ' ' ORDER BY p.i) AS kept FROM p WHERE NOT EXISTS (SELECT 1 FROM (SELECT doc_id, unnest(gone) AS i FROM g) o WHERE o.doc_id = p.doc_id AND o.i = p.i) GROUP BY p.doc_id)
SELECT w.doc_id, len(w)::BIGINT AS n_words, coalesce(len(gone), 0)::BIGINT AS n_removed, sha256(CASE WHEN g.doc_id IS NULL THEN array_to_string(w, ' ') ELSE coalesce(t.kept, '') END) AS kept_sha256
FROM w LEFT JOIN g USING (doc_id) LEFT JOIN t USING (doc_id)"""
