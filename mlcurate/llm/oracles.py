"""SQL twins of the queries that SQL can express (dialect of the checking engine)."""

from __future__ import annotations

from mlcurate.llm import licenses, pii

_PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)",
    "card": r"[0-9](?:[\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_DIGITS = "regexp_replace(m, '[^0-9]', '', 'g')"
_LUHN = f"""(list_sum(list_transform(range(1, length({_DIGITS}) + 1), lambda i:
    CASE WHEN i % 2 = 1 THEN substr(reverse({_DIGITS}), i, 1)::INT
         WHEN substr(reverse({_DIGITS}), i, 1)::INT > 4 THEN substr(reverse({_DIGITS}), i, 1)::INT * 2 - 9
         ELSE substr(reverse({_DIGITS}), i, 1)::INT * 2 END)) % 10 = 0)"""
_VALID = {
    "email": "true",
    "ip": "len(list_filter(string_split(m, '.'), lambda x: length(ltrim(x, '0')) > 3 OR coalesce(try_cast(right(x, 3) AS INT), 0) > 255)) = 0",
    "card": f"length({_DIGITS}) BETWEEN 13 AND 19 AND {_LUHN}",
    "phone": f"length({_DIGITS}) BETWEEN 9 AND 15",
}


def _kind(i: int, kind: str) -> str:
    p = _PLAIN[kind]
    return f"""SELECT doc_id, {i} AS o, '{kind}' AS kind, m, start, start + length(m) AS stop FROM (
    SELECT doc_id, m[i] AS m, list_sum(list_transform(p[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS start FROM (
        SELECT doc_id, m, p, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, regexp_extract_all(text, '{p}') AS m, string_split_regex(text, '{p}') AS p FROM documents))) WHERE {_VALID[kind]}"""


#: Base columns only; op6_pii_base is the query's base part.
PII_BASE = "WITH sp AS (" + " UNION ALL ".join(_kind(i, k) for i, k in enumerate(pii.BASE)) + ") SELECT d.doc_id, " + ", ".join(f"count(*) FILTER (kind = '{k}') AS n_{k}" for k in pii.BASE) + ", sha256(coalesce(string_agg(kind || ':' || start::BIGINT || ':' || stop::BIGINT, ',' ORDER BY o, start), '')) AS base_sha256 FROM documents d LEFT JOIN sp USING (doc_id) GROUP BY d.doc_id"

_WORDS = r"regexp_extract_all(regexp_replace(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+', ' ', 'g'), '[^ ]+')"
_PLACES = " UNION ALL ".join(f"SELECT doc_id, '{label}' AS label, unnest(list_filter(range(1, len(w) + 1), lambda i: {' AND '.join(f'coalesce(w[i + {k}] = {x!r}, false)' for k, x in enumerate(p.split()))})) - 1 AS spot FROM wd" for p, label in licenses.PHRASES.items())
_TEMPLATES = ", ".join(f"('{label}', {sorted(set(t.split()))!r})" for label, t in licenses.TEMPLATES)
LICENSES = rf"""WITH wd AS (SELECT doc_id, {_WORDS} AS w FROM documents),
pl AS ({_PLACES}),
bl AS (SELECT doc_id, list_distinct(v[i + 1 : i + {licenses.BLOCK}]) AS b FROM (SELECT doc_id, w AS v, unnest(range(0, greatest(len(w) - {licenses.BLOCK // 2}, 1), {licenses.BLOCK // 2})) AS i FROM wd WHERE len(w) > 0)),
tm AS (SELECT * FROM (VALUES {_TEMPLATES}) t(label, own)),
mt AS (SELECT doc_id, label, len(list_intersect(b, own)) / len(own) AS c FROM bl, tm WHERE len(list_intersect(b, own)) >= {licenses.THETA} * len(own) - 1e-9),
lb AS (SELECT doc_id, array_to_string(list_sort(list(DISTINCT label)), ',') AS labels FROM (SELECT doc_id, label FROM pl UNION ALL SELECT doc_id, label FROM mt) GROUP BY doc_id),
bs AS (SELECT doc_id, count(*) AS n, min(spot) AS a, max(spot) AS z, array_to_string(list_sort(list(DISTINCT label)), ',') AS labels FROM pl GROUP BY doc_id)
SELECT wd.doc_id, len(w)::BIGINT AS n_words, coalesce(bs.n, 0) AS n_base, bs.a AS first_word, bs.z AS last_word, coalesce(bs.labels, '') AS base_labels, coalesce(lb.labels, '') AS labels,
    CASE WHEN bs.n > 0 THEN 1.0::DOUBLE ELSE round(coalesce(mx.c, 0), 6) END AS score
FROM wd LEFT JOIN bs USING (doc_id) LEFT JOIN lb USING (doc_id) LEFT JOIN (SELECT doc_id, max(c) AS c FROM mt GROUP BY doc_id) mx USING (doc_id)"""

JACCARD = r"""WITH RECURSIVE wd AS (SELECT doc_id, text, regexp_extract_all(lower(text), '[\p{L}\p{N}_]+') AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' ')) END) AS s FROM wd),
sz AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
pr AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM sh a JOIN sh b USING (s) WHERE a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
ln AS (SELECT x, y FROM pr JOIN sz p ON p.doc_id = x JOIN sz q ON q.doc_id = y WHERE k >= 0.8 * (p.n + q.n - k) - 1e-12),
reach AS (SELECT doc_id AS id, doc_id AS c FROM documents UNION SELECT reach.id, ln.y FROM reach JOIN ln ON ln.x = reach.c),
cl AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS class_id, count(*) OVER (PARTITION BY text) AS n_copies FROM documents)
SELECT cl.doc_id, class_id, n_copies, (SELECT count(*) FROM ln WHERE x = cl.doc_id) AS n_links, (SELECT min(c) FROM reach WHERE id = cl.doc_id) AS group_id FROM cl"""
