"""Language identification, confidence cuts, sweeps and baselines; URL filtering and extraction."""

from __future__ import annotations

from pyspark.sql import functions as F

from mlcurate.functions import html, urls
from mlcurate.io import table, with_snapshot
from mlcurate.operators import lid
from mlcurate.session import settle
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

#: pred: label, confidence and margin of every document by a model of the even doc_ids.
_GRAMS = r"""src AS (SELECT doc_id, lang, string_split(' ' || trim(regexp_replace(lower(text), '\s+', ' ', 'g')) || ' ', '') AS l FROM documents),
gr AS (SELECT doc_id, lang, g, count(*) AS k FROM (SELECT doc_id, lang, unnest(list_transform(range(1, len(l) - 1), lambda i: l[i] || l[i + 1] || l[i + 2])) AS g FROM src) GROUP BY ALL)"""


def _pred(where: str = "true", name: str = "pred") -> str:
    return f"""tc AS (SELECT lang AS label, g, sum(k) AS c FROM gr GROUP BY ALL),
vs AS (SELECT count(DISTINCT g) AS v FROM tc), tt AS (SELECT label, sum(c) AS t FROM tc WHERE {where} GROUP BY label),
sc AS (SELECT doc_id, tt.label, sum(k * ln((coalesce(c, 0) + 0.5) / (t + 0.5 * v))) / sum(k) AS s FROM gr CROSS JOIN tt CROSS JOIN vs LEFT JOIN tc ON tc.g = gr.g AND tc.label = tt.label GROUP BY ALL),
sm AS (SELECT doc_id, label, exp(0.5 * (s - max(s) OVER (PARTITION BY doc_id))) AS e FROM sc),
pr AS (SELECT doc_id, label, e / sum(e) OVER (PARTITION BY doc_id) AS p FROM sm),
rk AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY p DESC, label DESC) AS r, lead(p) OVER (PARTITION BY doc_id ORDER BY p DESC, label DESC) AS nxt FROM pr),
{name} AS (SELECT doc_id, label, p AS conf, p - coalesce(nxt, 0) AS margin FROM rk WHERE r = 1)"""


PRED = f"{_GRAMS},\n{_pred()}"
_CUT = "cut AS (SELECT label, quantile_cont(conf, 0.5) AS med, avg(conf) AS mean, stddev_pop(conf) AS std FROM pred GROUP BY label)"


def predictions(spark, sf_dir, labels=None):
    docs = table(spark, sf_dir, "documents")
    return settle(lid.NgramBayes().fit(docs).predict(docs, labels=labels), "pred")


@query(S.with_(PRED, "SELECT doc_id, label, round(conf, 6) AS conf, round(margin, 6) AS margin FROM pred"))
def w_lid_nb_predict(spark, sf_dir):
    return predictions(spark, sf_dir).select("doc_id", "label", F.round("conf", 6).alias("conf"), F.round("margin", 6).alias("margin"))


@query(S.with_(PRED, "SELECT doc_id, label, round(conf, 6) AS conf FROM pred"))
def w_lid_nb_arrow(spark, sf_dir):
    """The same labels without a shuffle."""
    docs = table(spark, sf_dir, "documents")
    return lid.NgramBayes().fit(docs).predict_arrow(docs).select("doc_id", "label", F.round("conf", 6).alias("conf"))


@query(S.with_(PRED, "SELECT lang, label, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY lang), 6) AS share FROM pred JOIN documents USING (doc_id) GROUP BY lang, label"))
def w_lid_confusion(spark, sf_dir):
    return lid.cousin_matrix(predictions(spark, sf_dir), table(spark, sf_dir, "documents"))


@query(S.with_(f"{_GRAMS},\n" + _pred("label <> 'es'"), "SELECT lang, label, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY lang), 6) AS share FROM pred JOIN documents USING (doc_id) GROUP BY lang, label"))
def w_lid_cousin(spark, sf_dir):
    """A model without Spanish: where do Spanish documents go?"""
    docs = table(spark, sf_dir, "documents")
    model = lid.NgramBayes().fit(docs)
    return lid.cousin_matrix(model.predict(docs, labels=["de", "en", "fr"]), docs)


@query(S.with_(PRED, """SELECT lang, round(coalesce(tp / nullif(m, 0), 0), 6) AS "precision", round(tp / n, 6) AS recall, round(coalesce(2 * tp / nullif(n + m, 0), 0), 6) AS f1 FROM
(SELECT lang, count(*) AS n, count(*) FILTER (label = lang) AS tp FROM pred JOIN documents USING (doc_id) GROUP BY lang) JOIN (SELECT d.lang, count(p.label) AS m FROM (SELECT DISTINCT lang FROM documents) d LEFT JOIN pred p ON p.label = d.lang GROUP BY d.lang) USING (lang)"""))
def w_lid_quality(spark, sf_dir):
    return lid.quality(predictions(spark, sf_dir), table(spark, sf_dir, "documents"))


@query()
def w_lid_softmax(spark, sf_dir):
    """Baseline: hashed n-grams and a linear classifier, fitted on even doc_ids; quality is that on the others."""
    docs = table(spark, sf_dir, "documents")
    model = lid.HashedSoftmax().fit(docs.where("doc_id % 2 = 0"))
    rest = docs.where("not (doc_id % 2 <=> 0)")
    return lid.quality(model.predict(rest), rest)


@query(S.with_(PRED, "SELECT lang, count(*) FILTER (label = 'en' AND conf >= 0.65) AS n_english, count(*) FILTER (NOT (label = 'en' AND conf >= 0.65)) AS n_rest FROM pred JOIN documents USING (doc_id) GROUP BY lang"))
def w_english_split(spark, sf_dir):
    docs, pred = table(spark, sf_dir, "documents"), predictions(spark, sf_dir)
    english, rest = lid.split_english(docs, pred)
    both = english.select("lang", F.lit(1).alias("e")).unionAll(rest.select("lang", F.lit(0).alias("e")))
    return both.groupBy("lang").agg(F.count_if(F.col("e") == 1).alias("n_english"), F.count_if(F.col("e") == 0).alias("n_rest"))


@query(S.with_(f"{PRED},\n{_CUT}", "SELECT label, round(med, 6) AS center, round(std, 6) AS std, round(least(0.9, greatest(0.3, med - std)), 6) AS cut FROM cut"))
def w_lid_cut_adaptive(spark, sf_dir):
    return lid.adaptive_cut(predictions(spark, sf_dir))


@query(S.with_(f"{PRED},\n{_CUT}", "SELECT label, round(mean, 6) AS center, round(std, 6) AS std, round(least(0.9, greatest(0.3, mean - std)), 6) AS cut FROM cut"))
def w_lid_cut_mean(spark, sf_dir):
    return lid.adaptive_cut(predictions(spark, sf_dir), center="mean")


def _fixed(t):
    @query(S.with_(PRED, f"SELECT label, count(*) AS n FROM pred WHERE round(conf, 6) >= {t} GROUP BY label"), f"w_lid_cut_fixed{round(t * 100)}")
    def run(spark, sf_dir):
        pred = predictions(spark, sf_dir)
        return lid.apply_cut(pred, lid.fixed_cut(pred, t)).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


for _t in (0.5, 0.7):
    _fixed(_t)


@query(S.with_(f"{PRED},\n{_CUT}", "SELECT label, count(*) AS n, count(*) FILTER (round(conf, 6) >= round(least(0.9, greatest(0.3, med - std)), 6)) AS n_kept FROM pred JOIN cut USING (label) GROUP BY label"))
def w_lid_retention(spark, sf_dir):
    pred = predictions(spark, sf_dir)
    kept = lid.apply_cut(pred, lid.adaptive_cut(pred)).groupBy("label").agg(F.count(F.lit(1)).alias("n_kept"))
    return pred.groupBy("label").agg(F.count(F.lit(1)).alias("n")).join(kept, "label", "left").select("label", "n", F.coalesce("n_kept", F.lit(0)).alias("n_kept"))


_STEPS = ", ".join(f"{round(0.05 * i, 6)}" for i in range(20))


@query(S.with_(f"""{PRED},
q AS (SELECT label, unnest(list_concat(quantile_cont(conf, [{_STEPS}]), [0.7, 0.8, 0.9])) AS t FROM pred GROUP BY label),
th AS (SELECT DISTINCT label, round(t, 6) AS threshold FROM q)""", "SELECT label, threshold, round(avg((round(conf, 6) < threshold)::INT), 6) AS removed FROM th JOIN pred USING (label) GROUP BY label, threshold"))
def w_lid_sweep(spark, sf_dir):
    return lid.sweep(predictions(spark, sf_dir))


_RANGE = f"""{PRED},\n{_CUT},
q AS (SELECT label, unnest(list_concat(quantile_cont(conf, [{_STEPS}]), [0.7, 0.8, 0.9])) AS t FROM pred GROUP BY label),
th AS (SELECT DISTINCT label, round(t, 6) AS threshold FROM q),
gd AS (SELECT lang AS label, count(*) AS n FROM documents GROUP BY lang),
fs AS (SELECT label, threshold, round(2 * count(*) FILTER (d.lang = label) / (count(*) + any_value(gd.n)), 6) AS f1 FROM th JOIN pred USING (label) JOIN documents d USING (doc_id) JOIN gd USING (label) WHERE round(conf, 6) >= threshold GROUP BY label, threshold),
rg AS (SELECT label, min(threshold) AS lo, max(threshold) AS hi FROM fs JOIN (SELECT label, max(f1) AS f1 FROM fs GROUP BY label) USING (label, f1) GROUP BY label),
fm AS (SELECT label, round(least(0.9, greatest(0.3, med - std)), 6) AS formula FROM cut)"""


@query(S.with_(_RANGE, "SELECT label, lo, hi, formula, formula >= lo - 0.005 AND formula <= coalesce(hi, 1.0) + 0.005 AS inside FROM rg JOIN fm USING (label)"))
def w_lid_in_range(spark, sf_dir):
    """Does the formula's cut lie among the cuts that score best?"""
    pred = predictions(spark, sf_dir)
    ranges = lid.best_ranges(pred, table(spark, sf_dir, "documents"))
    return lid.in_range(ranges.join(lid.adaptive_cut(pred).select("label", F.col("cut").alias("formula")), "label"))


BLOCK = urls.Blocklist(domains=("cheap-pills.example.com", "tionsh.example.net"), urls=("http://thther.example.org/fr/414",), strict=("bets",), soft=("m", "blog", "feed", "ref"))
_HOST = "lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]*)', 1))"
_REASON = f"""CASE WHEN url IN ('http://thther.example.org/fr/414') THEN 'url'
    WHEN list_has_any(list_transform(range(1, len(string_split({_HOST}, '.')) + 1), lambda i: array_to_string(string_split({_HOST}, '.')[i:], '.')), ['cheap-pills.example.com', 'tionsh.example.net']) THEN 'domain'
    WHEN list_contains(regexp_extract_all(lower(url), '[a-z]+'), 'bets') THEN 'strict'
    WHEN len(list_intersect(list_distinct(regexp_extract_all(lower(url), '[a-z]+')), ['m', 'blog', 'feed', 'ref'])) >= 2 THEN 'soft' END"""


@query(f"SELECT page_id, {_REASON} AS reason FROM pages")
def w_url_block(spark, sf_dir):
    return urls.blocked_by(table(spark, sf_dir, "pages").select("page_id", "url"), BLOCK).select("page_id", "reason")


def _html_sql() -> str:
    x = "regexp_replace(html, '(?s)<!--.*?-->', '', 'g')"
    for tag in html.DROPPED:
        x = f"regexp_replace({x}, '(?is)<{tag}[ >].*?</{tag}>', '', 'g')"
    x = f"""regexp_replace({x}, '(?is)<div class="ad">.*?</div>', '', 'g')"""
    x = f"regexp_replace({x}, '(?i)</?(?:{html.BREAKS})(?: [^>]*)?/?>', chr(10), 'g')"
    x = f"regexp_replace({x}, '<[^>]*>', '', 'g')"
    for k, v in html.ENTITIES.items():
        v = v.replace("'", "''")
        x = f"replace({x}, '{k}', '{v}')"
    x = f"regexp_replace({x}, '[ \\t]+', ' ', 'g')"
    return f"regexp_replace(regexp_replace(regexp_replace({x}, ' ?\\n ?', chr(10), 'g'), '\\n+', chr(10), 'g'), '^[ \\n]+|[ \\n]+$', '', 'g')"


@query(f"SELECT page_id, trim(regexp_extract(html, '(?is)<title>(.*?)</title>', 1)) AS title, length(x)::BIGINT AS n_chars, md5(x) AS text_md5 FROM (SELECT page_id, html, {_html_sql()} AS x FROM pages)")
def w_extract_sql(spark, sf_dir):
    x = html.extract(table(spark, sf_dir, "pages"))
    return x.select("page_id", "title", F.length("text").cast("long").alias("n_chars"), F.md5("text").alias("text_md5"))


@query()
def w_extract_parser(spark, sf_dir):
    return html.extract(table(spark, sf_dir, "pages"), "arrow")


@query(f"SELECT page_id % 12 AS snapshot, coalesce({_REASON}, 'kept') AS reason, count(*) AS n FROM pages GROUP BY ALL")
def w_funnel(spark, sf_dir):
    pages = with_snapshot(table(spark, sf_dir, "pages").select("page_id", "url"), F.pmod(F.col("page_id"), F.lit(12)))
    return urls.blocked_by(pages, BLOCK).groupBy("snapshot", F.coalesce("reason", F.lit("kept")).alias("reason")).agg(F.count(F.lit(1)).alias("n"))
