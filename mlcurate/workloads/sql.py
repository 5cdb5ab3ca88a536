"""SQL fragments that oracles share (dialect of the checking engine)."""

from __future__ import annotations

from mlcurate.operators.metrics import DUP, FIXED, RULES, TERMINAL, TOP

WORDS = r"regexp_extract_all(lower(text), '[\p{L}\p{M}\p{N}]+')"
TOKENS = r"regexp_extract_all(lower(text), '[\p{L}\p{M}\p{N}]+|[^\s\p{L}\p{M}\p{N}]+')"


def grams(w: str, n) -> str:
    """n-grams of a word list."""
    return f"list_transform(range(1, len({w}) - {n} + 2), lambda i: array_to_string({w}[i:i + {n} - 1], ' '))"


_TERMINAL = ", ".join("'" + c.replace("'", "''") + "'" for c in TERMINAL)

_BASE = f"""
base AS MATERIALIZED (SELECT doc_id, lang, text, {WORDS} AS w, {TOKENS} AS t,
    list_filter(list_transform(string_split(text, chr(10)), lambda x: trim(x)), lambda x: x <> '') AS l FROM documents),
mline AS (SELECT doc_id, len(l)::BIGINT AS n_lines,
    round((len(l) - len(list_distinct(l))) / greatest(len(l), 1), 9) AS dup_line_ratio,
    round((length(array_to_string(l, '')) - length(array_to_string(list_distinct(l), ''))) / greatest(length(array_to_string(l, '')), 1), 9) AS dup_line_char_ratio,
    round(len(list_filter(l, lambda x: NOT right(x, 1) IN ({_TERMINAL}))) / greatest(len(l), 1), 9) AS nonpunct_line_ratio,
    round(len(list_filter(l, lambda x: left(x, 1) IN ('•', '‣', '-', '*', '▪', '●'))) / greatest(len(l), 1), 9) AS bullet_line_ratio,
    round(len(list_filter(l, lambda x: x LIKE '%…' OR x LIKE '%...')) / greatest(len(l), 1), 9) AS ellipsis_line_ratio FROM base),
mword AS (SELECT doc_id, len(w)::BIGINT AS n_words,
    round(length(array_to_string(w, '')) / greatest(len(w), 1), 9) AS avg_word_len,
    round(CASE WHEN len(w) > 0 THEN len(l) / len(w) ELSE 0 END, 9) AS lines_per_word,
    round(len(regexp_extract_all(text, '#|…|\\.\\.\\.')) / greatest(len(w), 1), 9) AS symbol_word_ratio,
    round(len(list_filter(t, lambda x: NOT regexp_matches(x, '\\p{{L}}'))) / greatest(len(t), 1), 9) AS nonalpha_word_ratio FROM base)"""

_REP = f"""
tot AS (SELECT doc_id, greatest(length(array_to_string(w, '')), 1) AS chars FROM base),
ws AS MATERIALIZED (SELECT doc_id, i, x AS x0, {", ".join(f"lead(x, {k}) OVER o AS x{k}" for k in range(1, max(DUP)))} FROM (SELECT doc_id, unnest(w) AS x, unnest(range(1, len(w) + 1)) AS i FROM base) WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
gr AS MATERIALIZED ({" UNION ALL ".join(f"SELECT doc_id, {n}::BIGINT AS n, concat_ws(' ', {', '.join(f'x{k}' for k in range(n))}) AS s, i FROM ws WHERE x{n - 1} IS NOT NULL" for n in (*TOP, *DUP))}),
gc AS MATERIALIZED (SELECT doc_id, n, s, count(*) AS c, length(replace(any_value(s), ' ', '')) AS k FROM gr GROUP BY doc_id, n, s),
gt AS (SELECT doc_id, n, max(c) AS mc FROM gc WHERE n <= {max(TOP)} GROUP BY doc_id, n),
top AS (SELECT gc.doc_id, gc.n, round(CASE WHEN any_value(mc) > 1 THEN any_value(mc) * max(k) / any_value(chars) ELSE 0 END, 9) AS v
    FROM gc JOIN gt ON gc.doc_id = gt.doc_id AND gc.n = gt.n AND gc.c = gt.mc JOIN tot ON tot.doc_id = gc.doc_id GROUP BY gc.doc_id, gc.n),
wl AS MATERIALIZED (SELECT doc_id, unnest(list_transform(w, lambda x: length(x))) AS k, unnest(range(1, len(w) + 1)) AS p FROM base),
cov AS MATERIALIZED (SELECT DISTINCT gr.doc_id, gr.n, unnest(range(gr.i, gr.i + gr.n)) AS p FROM gr JOIN gc ON gr.doc_id = gc.doc_id AND gr.n = gc.n AND gr.s = gc.s WHERE c > 1 AND gr.n >= {min(DUP)}),
dup AS (SELECT cov.doc_id, cov.n, round(sum(k) / any_value(chars), 9) AS v FROM cov JOIN wl ON cov.doc_id = wl.doc_id AND cov.p = wl.p JOIN tot ON tot.doc_id = cov.doc_id GROUP BY cov.doc_id, cov.n),
mrep AS MATERIALIZED (SELECT base.doc_id, {", ".join(f"coalesce(max(top.v) FILTER (top.n = {n}), 0) AS top_{n}gram_char_ratio" for n in TOP)} FROM base LEFT JOIN top ON base.doc_id = top.doc_id GROUP BY base.doc_id),
mdup AS MATERIALIZED (SELECT base.doc_id, {", ".join(f"coalesce(max(dup.v) FILTER (dup.n = {n}), 0) AS dup_{n}gram_char_ratio" for n in DUP)} FROM base LEFT JOIN dup ON base.doc_id = dup.doc_id GROUP BY base.doc_id)"""

LINES, REP = _BASE.strip(), _REP.strip()
#: m: every metric of every document.
METRICS = f"{LINES},\n{REP},\nm AS MATERIALIZED (SELECT * FROM (SELECT doc_id, lang FROM documents) d JOIN mline USING (doc_id) JOIN mword USING (doc_id) JOIN mrep USING (doc_id) JOIN mdup USING (doc_id))"

_LONG = " UNION ALL ".join(f"SELECT doc_id, lang, '{r}' AS rule, '{g}' AS grp, '{d}' AS direction, {float(t)}::DOUBLE AS t_en, {m}::DOUBLE AS v FROM m" for r, (g, m, d, t) in RULES.items())
#: st: statistics by reference, language and rule; cuts: thresholds by every method.
CUTS = f"""{METRICS},
lg AS ({_LONG}),
enough AS (SELECT lang FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0 GROUP BY lang HAVING count(*) >= 20),
refs AS MATERIALIZED (SELECT 'cc' AS ref, * FROM lg UNION ALL SELECT 'wiki' AS ref, lg.* FROM lg JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0 AND lang IN (FROM enough)
    UNION ALL SELECT 'wiki' AS ref, lg.* FROM lg WHERE lang NOT IN (FROM enough)),
st AS MATERIALIZED (SELECT ref, lang, rule, grp, direction, t_en, avg(v) AS mean, stddev_pop(v) AS std, quantile_cont(v, 0.5) AS med, list(v ORDER BY v) AS vs, count(*) AS n,
    avg(CASE WHEN (direction = 'max' AND v > t_en) OR (direction = 'min' AND v < t_en) THEN 1.0 ELSE 0.0 END) AS r FROM refs GROUP BY ALL),
en AS (SELECT ref, rule, mean AS en_mean, std AS en_std, med AS en_med, r AS en_r FROM st WHERE lang = 'en'),
s2 AS (SELECT st.*, en_mean, en_std, en_med, CASE WHEN direction = 'max' THEN 1 - en_r ELSE en_r END AS pq, CASE WHEN direction = 'max' THEN 1 - 0.1::DOUBLE ELSE 0.1::DOUBLE END AS pt FROM st JOIN en USING (ref, rule)),
s3 AS (SELECT *, floor(pq * (n - 1))::BIGINT AS lq, floor(pt * (n - 1))::BIGINT AS lt FROM s2),
cuts AS (SELECT method, ref, lang, rule, grp, direction, round(c, 9) AS threshold FROM (
    SELECT 'mean_std' AS method, *, CASE WHEN en_std > 0 THEN mean + std * (t_en - en_mean) / en_std END AS c FROM s3
    UNION ALL SELECT 'median_std', *, CASE WHEN en_std > 0 THEN med + std * (t_en - en_med) / en_std END FROM s3
    UNION ALL SELECT 'quantile', *, vs[lq + 1] + (vs[least(lq + 2, n)] - vs[lq + 1]) * (pq * (n - 1) - lq) FROM s3
    UNION ALL SELECT 'tail', *, vs[lt + 1] + (vs[least(lt + 2, n)] - vs[lt + 1]) * (pt * (n - 1) - lt) FROM s3
    UNION ALL SELECT 'median_ratio', *, CASE WHEN en_med <> 0 THEN t_en * med / en_med END FROM s3
    UNION ALL SELECT 'english', *, t_en FROM s3
    UNION ALL SELECT 'none', *, NULL FROM s3))"""
#: grid: cuts of the compared combinations only.
GRID = f"""{CUTS},
grid AS (SELECT * FROM cuts WHERE method IN ('tail', 'mean_std', 'median_ratio', 'quantile')
    UNION ALL SELECT method, '-' AS ref, lang, rule, grp, direction, threshold FROM cuts WHERE method IN ('none', 'english') AND ref = 'cc'),
dec AS (SELECT doc_id, g.lang, g.grp, g.method, g.ref, g.rule, coalesce(CASE WHEN g.direction = 'max' THEN v > threshold ELSE v < threshold END, false) AS bad
    FROM grid g JOIN lg ON lg.lang = g.lang AND lg.rule = g.rule),
docbad AS (SELECT doc_id, lang, grp, method, ref, max(bad) AS bad FROM dec GROUP BY ALL),
rates AS (SELECT * FROM (SELECT grp, method, ref, lang, round(avg(bad::INT), 6) AS removed FROM docbad GROUP BY ALL)
    JOIN (SELECT grp, method, ref, lang, round(max(x), 6) AS worst FROM (SELECT grp, method, ref, lang, rule, avg(bad::INT) AS x FROM dec GROUP BY ALL) GROUP BY ALL) USING (grp, method, ref, lang)),
ok AS (SELECT grp, method, ref, (max(worst) <= 0.75 AND max(removed) > 0 AND any_value(defined)) OR method = 'none' AS valid FROM rates
    JOIN (SELECT grp, method, ref, count(*) FILTER (threshold IS NULL) = 0 AS defined FROM grid GROUP BY ALL) USING (grp, method, ref) GROUP BY grp, method, ref),
tally AS (SELECT grp, method, ref, lang, count(*) FILTER (bad AND quality = 0) AS tp, count(*) FILTER (bad AND quality = 1) AS fp, count(*) FILTER (NOT bad AND quality = 0) AS fn FROM docbad JOIN labels USING (doc_id) GROUP BY ALL),
score AS (SELECT grp, method, ref, lang, round(CASE WHEN tp + fp + fn > 0 THEN 2 * tp / (2 * tp + fp + fn) ELSE 0 END, 6) AS score FROM tally),
ranks AS (SELECT grp, method, ref, round(avg(r), 6) AS avg_rank FROM (SELECT s.*, rank() OVER (PARTITION BY s.grp, lang ORDER BY score DESC) AS r FROM score s JOIN ok USING (grp, method, ref) WHERE valid) GROUP BY ALL)"""

#: rk: words with a letter by rank in their language, from their counts (wc).
FREQUENT = """
fr AS (SELECT lang, token, n, n / total AS freq FROM wc JOIN (SELECT lang, sum(n) AS total FROM wc GROUP BY lang) USING (lang) WHERE regexp_matches(token, '^[\\p{L}\\p{M}]+$')),
rk AS (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, token) AS rank FROM fr)""".strip()
_FREQ = f"wc AS (SELECT lang, token, count(*) AS n FROM (SELECT lang, unnest({WORDS}) AS token FROM ref) GROUP BY ALL),\n{FREQUENT}"
CLEAN = "SELECT documents.* FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0"
#: sw: stopwords of the clean reference.
STOP = f"ref AS ({CLEAN}),\n{_FREQ},\nsw AS (SELECT lang, token, n, freq FROM rk WHERE freq >= 0.008 OR rank <= 8)"
STOP_ALL = f"ref AS (SELECT * FROM documents),\n{_FREQ},\nsw AS (SELECT lang, token, n, freq FROM rk WHERE freq >= 0.008 OR rank <= 8)"
HITS = f"hits AS (SELECT doc_id, any_value(d.lang) AS lang, count(sw.token)::BIGINT AS n_stopwords FROM (SELECT doc_id, lang, unnest(list_distinct({WORDS})) AS token FROM documents) d LEFT JOIN sw USING (lang, token) GROUP BY doc_id)"

_RECIPE = "((grp = 'LQ' AND method = 'tail' AND ref = 'wiki') OR (grp = 'DQ' AND method = 'quantile' AND ref = 'wiki') OR (grp = 'RP' AND method = 'mean_std' AND ref = 'cc'))"
_FIXED = " UNION ALL ".join(f"SELECT doc_id, '{r}' AS rule, '{g}' AS grp FROM m WHERE {m} {'>' if d == 'max' else '<'} {float(t)}" for r, (g, m, d, t) in FIXED.items())
#: why: (doc_id, rule, grp) of every rule that the default recipe fails a document for; kept: flag of every document.
RECIPE = f"""{CUTS},
{STOP},
{HITS},
why AS (SELECT doc_id, rule, lg.grp FROM lg JOIN (SELECT lang, rule, threshold FROM cuts WHERE {_RECIPE}) USING (lang, rule) WHERE CASE WHEN direction = 'max' THEN v > threshold ELSE v < threshold END
    UNION ALL {_FIXED}
    UNION ALL SELECT d.doc_id, 'F8' AS rule, 'DQ' AS grp FROM documents d LEFT JOIN hits USING (doc_id) WHERE coalesce(n_stopwords, 0) < 2),
kept AS (SELECT d.doc_id, d.lang, count(rule) = 0 AS keep, coalesce(array_to_string(list_sort(list(rule) FILTER (rule IS NOT NULL)), ','), '') AS reasons FROM documents d LEFT JOIN why USING (doc_id) GROUP BY ALL)"""


def with_(ctes: str, select: str) -> str:
    return f"WITH RECURSIVE {ctes}\n{select}"
