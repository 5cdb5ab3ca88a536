"""Metrics, stopwords, thresholds, choice of methods, and the default recipe."""

from __future__ import annotations

from pyspark.sql import functions as F

from mlcurate.functions import scripts
from mlcurate.functions import words as W
from mlcurate.io import table
from mlcurate.operators import metrics as M
from mlcurate.operators import reports, selection, stopwords, thresholds
from mlcurate.session import settle
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

REP = [*M.REPETITION]


def clean(spark, sf_dir):
    """The clean reference: documents of good labelled quality that aren't toxic."""
    good = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    return table(spark, sf_dir, "documents").join(good, "doc_id", "left_semi")


def references(spark, sf_dir):
    """Metrics of both references, from one metrics table."""
    m = settle(M.compute(table(spark, sf_dir, "documents")), "metrics")
    good = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    return {"cc": m, "wiki": stopwords.resolve(m.join(good, "doc_id", "left_semi"), m)}


@query(S.with_(S.LINES, "SELECT doc_id, n_lines, dup_line_ratio, dup_line_char_ratio, nonpunct_line_ratio, bullet_line_ratio, ellipsis_line_ratio FROM mline"))
def w_metrics_lines(spark, sf_dir):
    df = M.line_metrics(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return df.select("doc_id", "n_lines", *[F.round(c, M.PLACES).alias(c) for c in ("dup_line_ratio", "dup_line_char_ratio", "nonpunct_line_ratio", "bullet_line_ratio", "ellipsis_line_ratio")])


@query(S.with_(S.LINES, "SELECT * FROM mword"))
def w_metrics_words(spark, sf_dir):
    df = M.word_metrics(M.line_metrics(table(spark, sf_dir, "documents").select("doc_id", "text")))
    return df.select("doc_id", "n_words", *[F.round(c, M.PLACES).alias(c) for c in ("avg_word_len", "lines_per_word", "symbol_word_ratio", "nonalpha_word_ratio")])


def _rep(spark, sf_dir, kind):
    df = M.repetition_metrics(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return df.select("doc_id", *[F.round(c, M.PLACES).alias(c) for c in REP if c.startswith(kind)])


@query(S.with_(f"{S.LINES},\n{S.REP}", "SELECT * FROM mrep"))
def w_metrics_rep_top(spark, sf_dir):
    return _rep(spark, sf_dir, "top")


@query(S.with_(f"{S.LINES},\n{S.REP}", "SELECT * FROM mdup"))
def w_metrics_rep_dup(spark, sf_dir):
    return _rep(spark, sf_dir, "dup")


@query(S.with_(S.CUTS, "SELECT ref, lang, rule, grp, direction, t_en, round(mean, 6) AS mean, round(med, 6) AS med, round(std, 6) AS std FROM st"))
def w_metric_stats(spark, sf_dir):
    parts = [thresholds.stats(m).select(F.lit(r).alias("ref"), "lang", "rule", "grp", "direction", "t_en", *[F.round(c, 6).alias(c) for c in ("mean", "med", "std")]) for r, m in references(spark, sf_dir).items()]
    return parts[0].unionByName(parts[1])


def _thresholds(method):
    @query(S.with_(S.CUTS, f"SELECT ref, lang, rule, grp, direction, round(threshold, 6) AS threshold FROM cuts WHERE method = '{method}'"), f"w_thr_{method}")
    def run(spark, sf_dir):
        parts = [thresholds.adapt(method, m).select(F.lit(r).alias("ref"), "lang", "rule", "grp", "direction", F.round("threshold", 6).alias("threshold")) for r, m in references(spark, sf_dir).items()]
        return parts[0].unionByName(parts[1])

    return run


for _m in ("none", "english", *thresholds.METHODS):
    _thresholds(_m)


@query()
def w_thr_sketched(spark, sf_dir):
    """The tail rule from sketches instead of exact percentiles, for scale."""
    return thresholds.adapt("tail", references(spark, sf_dir)["cc"], accuracy=10_000)


def _grid(spark, sf_dir):
    refs = references(spark, sf_dir)
    cuts = settle(selection.all_cuts(refs), "cuts")
    return refs["cc"], cuts


@query(S.with_(S.GRID, "SELECT grp, method, ref, lang, removed, worst FROM rates"))
def w_removal_rates(spark, sf_dir):
    m, cuts = _grid(spark, sf_dir)
    return selection.removal(m, cuts).select("grp", "method", "ref", "lang", "removed", "worst")


@query(S.with_(S.GRID, "SELECT grp, method, ref, valid FROM ok"))
def w_valid_combos(spark, sf_dir):
    m, cuts = _grid(spark, sf_dir)
    return selection.valid(selection.removal(m, cuts), cuts)


def _ranks(spark, sf_dir):
    m, cuts = _grid(spark, sf_dir)
    ok = settle(selection.valid(selection.removal(m, cuts), cuts), "valid")
    return selection.rank(selection.label_scores(m, cuts, table(spark, sf_dir, "labels")), ok)


@query(S.with_(S.GRID, "SELECT grp, method, ref, avg_rank FROM ranks"))
def w_rank_methods(spark, sf_dir):
    return _ranks(spark, sf_dir)


@query(S.with_(S.GRID, "SELECT grp, method, ref, avg_rank FROM ranks QUALIFY row_number() OVER (PARTITION BY grp ORDER BY avg_rank, method, ref) = 1"))
def w_select_methods(spark, sf_dir):
    return selection.choose(_ranks(spark, sf_dir))


@query(S.with_(S.STOP, "SELECT lang, token, n, round(freq, 6) AS freq FROM sw"))
def w_stopwords(spark, sf_dir):
    return stopwords.fit(clean(spark, sf_dir)).select("lang", "token", "n", F.round("freq", 6).alias("freq"))


@query(S.with_(S.STOP, "SELECT lang, token, n, round(freq, 6) AS freq FROM rk WHERE rank <= 8"))
def w_stopwords_topk(spark, sf_dir):
    return stopwords.topk(clean(spark, sf_dir)).select("lang", "token", "n", F.round("freq", 6).alias("freq"))


@query(S.with_(S.STOP_ALL, "SELECT s.lang, count(*) AS n_words, count(e.token) AS n_english, round(count(e.token) / count(*), 6) AS leak FROM sw s LEFT JOIN (SELECT token FROM sw WHERE lang = 'en') e USING (token) GROUP BY s.lang"))
def w_stopword_leak(spark, sf_dir):
    """How much English is in the lists when the reference isn't cleaned."""
    return stopwords.leakage(stopwords.fit(table(spark, sf_dir, "documents")))


@query(S.with_(f"{S.STOP},\n{S.HITS}", "SELECT d.doc_id, d.lang, coalesce(n_stopwords, 0) AS n_stopwords FROM documents d LEFT JOIN hits USING (doc_id)"))
def w_stopword_hits(spark, sf_dir):
    return stopwords.hits(table(spark, sf_dir, "documents"), stopwords.fit(clean(spark, sf_dir)))


@query("SELECT doc_id, CASE WHEN regexp_matches(text, '\\p{Latin}') THEN 'Latn' ELSE 'Zyyy' END AS script, CASE lang WHEN 'en' THEN 'eng' WHEN 'de' THEN 'deu' WHEN 'fr' THEN 'fra' ELSE 'spa' END || '_' || CASE WHEN regexp_matches(text, '\\p{Latin}') THEN 'Latn' ELSE 'Zyyy' END AS label FROM documents")
def w_script_dominant(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id", "lang", scripts.dominant(F.col("text")).alias("script"))
    return d.select("doc_id", "script", scripts.label(F.col("lang"), F.col("script")).alias("label"))


@query("SELECT doc_id, length(regexp_replace(text, '(?s)(?:^|\\n)(?:Les\\.|And ornd\\.)[ \\t]*(?:\\n.*)?$', '')) AS n_left FROM documents")
def w_ref_clean(spark, sf_dir):
    """Texts cut at headings; two frequent lines play their part."""
    return table(spark, sf_dir, "documents").select("doc_id", F.length(stopwords.cut_tail(F.col("text"), ["Les.", "And ornd."])).cast("long").alias("n_left"))


def recipe(spark, sf_dir):
    """(doc_id, lang, keep, reasons) by the default recipe, and the metrics."""
    refs = references(spark, sf_dir)
    stop = stopwords.hits(table(spark, sf_dir, "documents"), stopwords.fit(clean(spark, sf_dir)))
    return refs["cc"], selection.recipe_cuts(refs), stop


@query(S.with_(S.RECIPE, "SELECT doc_id, lang, keep, reasons FROM kept"))
def w_filter_apply(spark, sf_dir):
    m, cuts, stop = recipe(spark, sf_dir)
    return selection.apply(m, cuts, stop).select("doc_id", "lang", "keep", F.array_join("reasons", ",").alias("reasons"))


@query(S.with_(S.RECIPE, "SELECT lang, rule, count(*) AS n FROM why JOIN documents USING (doc_id) GROUP BY ALL"))
def w_filter_reasons(spark, sf_dir):
    m, cuts, stop = recipe(spark, sf_dir)
    return selection.apply(m, cuts, stop).select("lang", F.explode("reasons").alias("rule")).groupBy("lang", "rule").agg(F.count(F.lit(1)).alias("n"))


_GROUPS = {"LQ": ("LQ",), "DQ": ("DQ",), "RP": ("RP",), "all": ("LQ", "DQ", "RP")}


@query(S.with_(S.RECIPE, " UNION ALL ".join(f"SELECT '{k}' AS grp, d.lang, count(*) AS n, count(*) FILTER (doc_id NOT IN (SELECT doc_id FROM why WHERE grp IN ({', '.join(repr(x) for x in g)}))) AS n_kept FROM documents d GROUP BY d.lang" for k, g in _GROUPS.items())))
def w_filter_group_ablation(spark, sf_dir):
    m, cuts, stop = recipe(spark, sf_dir)
    cuts = settle(cuts, "cuts")
    parts = [selection.apply(m, cuts, stop, groups=g).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count_if("keep").alias("n_kept")).select(F.lit(k).alias("grp"), "lang", "n", "n_kept") for k, g in _GROUPS.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


_QUALITY = """SELECT lang, n, round(coalesce(tp / nullif(tp + fp, 0), 0), 6) AS "precision", round(coalesce(tp / nullif(tp + fn, 0), 0), 6) AS recall, round(coalesce(2 * tp / nullif(2 * tp + fp + fn, 0), 0), 6) AS f1,
    round(coalesce((tp * tn - fp * fn) / nullif(sqrt((tp + fp) * (tp + fn) * (tn + fp) * (tn + fn)), 0), 0), 6) AS mcc
FROM (SELECT lang, count(*) AS n, count(*) FILTER (keep AND quality = 1)::DOUBLE AS tp, count(*) FILTER (keep AND quality = 0)::DOUBLE AS fp, count(*) FILTER (NOT keep AND quality = 1)::DOUBLE AS fn, count(*) FILTER (NOT keep AND quality = 0)::DOUBLE AS tn FROM kept JOIN labels USING (doc_id) GROUP BY lang)"""


@query(S.with_(S.RECIPE, _QUALITY))
def w_filter_quality_f1(spark, sf_dir):
    m, cuts, stop = recipe(spark, sf_dir)
    return reports.label_quality(selection.apply(m, cuts, stop), table(spark, sf_dir, "labels"))


@query(S.with_(S.RECIPE, f"{_QUALITY} WHERE lang = 'es'"))
def w_unseen_transfer(spark, sf_dir):
    """The recipe, chosen without it, on the language held out."""
    m, cuts, stop = recipe(spark, sf_dir)
    return reports.label_quality(selection.apply(m, cuts, stop).where("lang = 'es'"), table(spark, sf_dir, "labels"))


@query(f"SELECT doc_id, len({S.WORDS})::BIGINT AS n_words, len({S.TOKENS})::BIGINT AS n_tokens, md5(array_to_string({S.WORDS}, ' ')) AS words_md5 FROM documents")
def w_words(spark, sf_dir):
    t = F.col("text")
    return table(spark, sf_dir, "documents").select("doc_id", F.size(W.words(t)).cast("long").alias("n_words"), F.size(W.tokens(t)).cast("long").alias("n_tokens"), F.md5(F.array_join(W.words(t), " ")).alias("words_md5"))
