"""Corpus reports, split, and stream-shaped aggregations over event time."""

from __future__ import annotations

from pyspark.sql import functions as F

from mlcurate.io import table
from mlcurate.operators import reports as R
from mlcurate.streaming import windows
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

_COMP = f"cp AS (SELECT lang, count(*) AS n_docs, sum(len({S.WORDS}))::BIGINT AS n_words, sum(strlen(text))::BIGINT AS n_bytes FROM documents GROUP BY lang)"


@query(S.with_(_COMP, "SELECT *, round(n_bytes / sum(n_bytes) OVER (), 6) AS byte_share FROM cp"))
def w_composition(spark, sf_dir):
    return R.composition(table(spark, sf_dir, "documents"))


@query("SELECT family, lang, count(*) AS n_docs, sum(strlen(text))::BIGINT AS n_bytes FROM (SELECT *, CASE WHEN lang IN ('en', 'de') THEN 'Germanic' ELSE 'Romance' END AS family FROM documents) GROUP BY ROLLUP (family, lang)")
def w_composition_rollup(spark, sf_dir):
    return R.composition_rollup(table(spark, sf_dir, "documents"))


@query("SELECT k::INT AS least, count(*) FILTER (CASE WHEN k = 500 THEN n >= k ELSE n > k END) AS n_labels FROM (SELECT lang, count(*) AS n FROM documents GROUP BY lang), (VALUES (106), (130), (500)) t(k) GROUP BY k")
def w_coverage(spark, sf_dir):
    return R.coverage(table(spark, sf_dir, "documents"), (106, 130, 500))


@query(S.with_(_COMP, "SELECT *, round(100000 / nullif(n_words, 0), 6) AS epochs, n_words >= 100000 AS enough FROM cp"))
def w_epochs(spark, sf_dir):
    return R.epochs(R.composition(table(spark, sf_dir, "documents")).drop("byte_share"), 100_000)


_PG = "pg AS (SELECT page_id, url, regexp_extract(url, '/(en|de|fr|es)/', 1) AS lang, lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]*)', 1)) AS host FROM pages)"


def pages(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", "url", F.regexp_extract("url", "/(en|de|fr|es)/", 1).alias("lang"))


@query(S.with_(f"{_PG},\ndm AS (SELECT lang, regexp_extract(host, '([^.]+\\.[^.]+)$', 1) AS domain, count(*) AS n FROM pg GROUP BY ALL)", "SELECT domain, count(*) AS n_langs, round(sum(n / t) / (SELECT count(DISTINCT lang) FROM pg), 6) AS mean_share FROM dm JOIN (SELECT lang, sum(n) AS t FROM dm GROUP BY lang) USING (lang) GROUP BY domain"))
def w_domains(spark, sf_dir):
    return R.domains(pages(spark, sf_dir))


_LABELS = {"example.com": "com", "example.net": "net"}


@query(S.with_(_PG, "SELECT lang, label, round(count(*) / any_value(t), 6) AS share, count(*) / any_value(t) > 0.5 AS over FROM (SELECT lang, CASE WHEN host = 'example.com' OR host LIKE '%.example.com' THEN 'com' WHEN host = 'example.net' OR host LIKE '%.example.net' THEN 'net' END AS label FROM pg) JOIN (SELECT lang, count(*) AS t FROM pg GROUP BY lang) USING (lang) WHERE label IS NOT NULL GROUP BY lang, label"))
def w_domain_share(spark, sf_dir):
    return R.domain_share(pages(spark, sf_dir), _LABELS)


_SPLIT = """hs AS (SELECT doc_id, lang, md5(coalesce(text, '')) AS h FROM documents),
nk AS (SELECT lang, CASE WHEN count(*) >= 100 THEN least(floor(count(*) * 0.05 + 1e-9), 100000) ELSE 0 END AS k FROM documents GROUP BY lang),
ft AS (SELECT lang, h FROM (SELECT lang, h, sum(count(*)) OVER (PARTITION BY lang ORDER BY h) AS r FROM hs GROUP BY lang, h) JOIN nk USING (lang) WHERE r <= k)"""


@query(S.with_(_SPLIT, "SELECT doc_id, lang, CASE WHEN (lang, h) IN (SELECT (lang, h) FROM ft) THEN 'test' ELSE 'train' END AS part FROM hs"))
def w_split(spark, sf_dir):
    return R.train_test(table(spark, sf_dir, "documents"), rate=0.05, min_docs=100)


@query("SELECT time_bucket(INTERVAL '6 hours', ts) AS window_start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY ALL")
def st_tumbling(spark, sf_dir):
    return windows.tumbling(table(spark, sf_dir, "events"), "6 hours")


@query("SELECT w AS window_start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM (SELECT *, unnest([time_bucket(INTERVAL '6 hours', ts), time_bucket(INTERVAL '6 hours', ts) - INTERVAL '6 hours']) AS w FROM events) GROUP BY ALL")
def st_sliding(spark, sf_dir):
    return windows.sliding(table(spark, sf_dir, "events"), "12 hours", "6 hours")


_SESS = """s1 AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '2 hours' THEN 0 ELSE 1 END AS fresh FROM events),
s2 AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS sid FROM s1)"""


@query(S.with_(_SESS, "SELECT user_id, min(ts) AS session_start, count(*) AS n FROM s2 GROUP BY user_id, sid"))
def st_session(spark, sf_dir):
    return windows.sessions(table(spark, sf_dir, "events"), "2 hours")


@query("SELECT doc_id, lang, len(regexp_extract_all(lower(text), '[\\p{L}\\p{M}\\p{N}]+')) >= 50 AS keep FROM documents")
def st_apply_filters(spark, sf_dir):
    """The batch equivalent of filtering a stream by fitted thresholds (here: the least number of words)."""
    return windows.apply_bounds(table(spark, sf_dir, "documents"), {"n_words": (50, None)})
