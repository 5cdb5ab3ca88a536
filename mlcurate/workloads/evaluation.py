"""Task statistics, score aggregation, answer scoring, tokenizer comparison, proxy tokenizers."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from mlcurate.io import table
from mlcurate.operators import answers, scores, signals, subword, tree
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

#: ts: score series from events: a task per type, a model per bucket of users, a step per day.
_TS = "ts AS (SELECT event_type AS task, user_id % 4 AS model, (extract(day FROM ts) - 1)::BIGINT AS step, round(avg(value) / 500, 9) AS score, 0.01::DOUBLE AS baseline FROM events GROUP BY ALL)"
_MONO = """rx AS (SELECT task, model, rank() OVER (PARTITION BY task, model ORDER BY step) + (count(*) OVER (PARTITION BY task, model, step) - 1) / 2 AS x, rank() OVER (PARTITION BY task, model ORDER BY score) + (count(*) OVER (PARTITION BY task, model, score) - 1) / 2 AS y FROM ts),
mono AS (SELECT task, round(avg(c), 6) AS monotonicity FROM (SELECT task, model, corr(x, y) AS c FROM rx GROUP BY ALL) GROUP BY task)"""
_SNR = "snr AS (SELECT task, round(avg(m / nullif(s, 0)), 6) AS snr FROM (SELECT task, step, avg(score) AS m, stddev_pop(score) AS s FROM ts GROUP BY ALL) GROUP BY task)"
_NONR = """fin AS (SELECT task, max(f) - any_value(b) AS gain FROM (SELECT task, model, arg_max(score, step) AS f, any_value(baseline) AS b FROM ts GROUP BY ALL) GROUP BY task),
spr AS (SELECT task, avg(s) AS s FROM (SELECT task, step, stddev_pop(score) AS s FROM ts GROUP BY task, step QUALIFY row_number() OVER (PARTITION BY task ORDER BY step DESC) <= 5) GROUP BY task),
nonr AS (SELECT task, round(gain / nullif(s, 0), 6) AS non_random FROM fin JOIN spr USING (task))"""


def series(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.groupBy(F.col("event_type").alias("task"), F.pmod("user_id", F.lit(4)).alias("model"), (F.dayofmonth("ts") - 1).cast("long").alias("step")).agg(F.round(F.avg("value") / 500, 9).alias("score"), F.lit(0.01).alias("baseline"))


@query(S.with_(f"{_TS},\n{_MONO}", "SELECT * FROM mono"))
def w_task_mono(spark, sf_dir):
    return signals.monotonicity(series(spark, sf_dir))


@query(S.with_(f"{_TS},\n{_SNR}", "SELECT * FROM snr"))
def w_task_snr(spark, sf_dir):
    return signals.snr(series(spark, sf_dir))


@query(S.with_(f"{_TS},\n{_NONR}", "SELECT * FROM nonr"))
def w_task_nonrandom(spark, sf_dir):
    return signals.non_random(series(spark, sf_dir))


_ORDER = """SELECT task, round(avg(tau), 6) AS ordering FROM (SELECT a.task, a.step, avg(sign(a.score - b.score) * sign(a.p - b.p)) AS tau FROM lg a JOIN lg b ON a.task = b.task AND a.step = b.step AND a.model < b.model WHERE a.step >= 15 AND a.p IS NOT NULL AND b.p IS NOT NULL GROUP BY ALL) GROUP BY task"""


@query(S.with_(f"{_TS},\nlg AS (SELECT *, lag(score) OVER (PARTITION BY task, model ORDER BY step) AS p FROM ts)", _ORDER))
def w_task_order(spark, sf_dir):
    return signals.ordering(series(spark, sf_dir), 15)


@query(S.with_(_TS, "SELECT task, round(stddev_pop(score), 6) AS noise FROM (SELECT *, rank() OVER (PARTITION BY task ORDER BY step DESC) AS r FROM ts) WHERE r = 1 GROUP BY task"))
def w_task_noise(spark, sf_dir):
    return signals.noise(series(spark, sf_dir))


@query(S.with_(f"{_TS},\n{_MONO},\n{_SNR},\n{_NONR}", "SELECT task, monotonicity, snr, non_random, coalesce(monotonicity >= -0.1 AND (snr >= 5 OR task = 'error') AND non_random >= 3, false) AS selected FROM mono JOIN snr USING (task) JOIN nonr USING (task)"))
def w_task_select(spark, sf_dir):
    return signals.select(series(spark, sf_dir), ("error",), -0.1, 5.0, 3.0)


_CATS = "CASE task WHEN 'click' THEN 'GK' WHEN 'view' THEN 'GK' WHEN 'error' THEN 'RC' ELSE 'NLU' END"


def categorised(spark, sf_dir):
    c = F.when(F.col("task").isin("click", "view"), "GK").when(F.col("task") == "error", "RC").otherwise("NLU")
    s = series(spark, sf_dir)
    return s.select("task", "model", "step", c.alias("category"), F.round(scores.rescale(F.col("score"), F.col("baseline")), 9).alias("score"))


@query(S.with_(_TS, "SELECT task, model, step, round(greatest(0, (score - baseline) / (1 - baseline)), 6)::DOUBLE AS score FROM ts"))
def w_rescale(spark, sf_dir):
    return categorised(spark, sf_dir).select("task", "model", "step", F.round("score", 6).alias("score"))


_RS = f"{_TS},\nrs AS (SELECT task, model, step, {_CATS} AS category, round(greatest(0, (score - baseline) / (1 - baseline)), 9)::DOUBLE AS score FROM ts),\nca AS (SELECT model, category, avg(score) AS score FROM rs GROUP BY ALL)"


@query(S.with_(_RS, "SELECT model, category, round(score, 6) AS score FROM ca UNION ALL SELECT model, 'all', round(avg(score), 6) FROM ca GROUP BY model"))
def w_macro(spark, sf_dir):
    return scores.macro(categorised(spark, sf_dir))


@query(S.with_(_TS, "SELECT task, model, step, round(avg(score) OVER (PARTITION BY task, model ORDER BY step ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smoothed FROM ts"))
def w_smooth(spark, sf_dir):
    return scores.smooth(series(spark, sf_dir)).select("task", "model", "step", "smoothed")


@query(S.with_(_RS, "SELECT model, count(*) FILTER (r = 1) AS wins FROM (SELECT *, rank() OVER (PARTITION BY task ORDER BY score DESC) AS r FROM (SELECT task, model, round(avg(score), 9) AS score FROM rs GROUP BY task, model)) GROUP BY model"))
def w_winner(spark, sf_dir):
    """In how many tasks each model has the best mean score."""
    s = categorised(spark, sf_dir).groupBy("task", "model").agg(F.round(F.avg("score"), 9).alias("score"))
    return scores.winners(s, "task", "model")


def choices(spark, sf_dir):
    x = table(spark, sf_dir, "lineitem")
    gold = F.min("l_linenumber").over(Window.partitionBy("l_orderkey"))
    return x.select(F.col("l_orderkey").alias("item"), F.col("l_linenumber").alias("choice"), (-F.col("l_extendedprice") / 10000).alias("logprob"), F.col("l_quantity").alias("n_tokens"), (5 * F.col("l_quantity")).alias("n_chars"), (-F.col("l_discount") * 10).alias("prior_logprob"), gold.alias("gold"))


_CH = "ch AS (SELECT l_orderkey AS item, l_linenumber AS choice, -l_extendedprice / 10000 AS p, l_quantity AS nt, 5 * l_quantity AS nc, -l_discount * 10 AS pp, min(l_linenumber) OVER (PARTITION BY l_orderkey) AS gold FROM lineitem)"


def _accuracy(norm, expr):
    @query(S.with_(f"{_CH},\nbest AS (SELECT item, choice, gold FROM ch QUALIFY row_number() OVER (PARTITION BY item ORDER BY round({expr}, 9) DESC, choice) = 1)", "SELECT count(*) AS n_items, count(*) FILTER (choice = gold) AS n_right, round(avg((choice = gold)::INT), 6) AS accuracy FROM best"), f"w_acc_{norm}")
    def run(spark, sf_dir):
        return answers.accuracy(choices(spark, sf_dir), norm)


for _n, _e in (("raw", "p"), ("char", "p / nullif(nc, 0)"), ("token", "p / nullif(nt, 0)"), ("pmi", "p - pp")):
    _accuracy(_n, _e)

_QA = "qa AS (SELECT u.conv_id, u.turn, a.text AS answer, u.text AS gold FROM conversations u JOIN conversations a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 WHERE u.role = 'user' AND a.role = 'assistant')"


def pairs(spark, sf_dir):
    c = table(spark, sf_dir, "conversations")
    u, a = c.where("role = 'user'").select("conv_id", "turn", F.col("text").alias("gold")), c.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("answer"))
    return u.join(a, ["conv_id", "turn"])


_CNT = lambda col, name: f"{name} AS (SELECT conv_id, turn, t, count(*) AS n FROM (SELECT conv_id, turn, unnest({S.WORDS.replace('text', col)}) AS t FROM qa) GROUP BY ALL)"


@query(S.with_(f"{_QA},\n{_CNT('answer', 'pa')},\n{_CNT('gold', 'pg')}", f"SELECT qa.conv_id, qa.turn, round(CASE WHEN len({S.WORDS.replace('text', 'any_value(answer)')}) + len({S.WORDS.replace('text', 'any_value(gold)')}) > 0 THEN 2 * coalesce(sum(least(pa.n, pg.n)) FILTER (pg.n IS NOT NULL), 0) / (len({S.WORDS.replace('text', 'any_value(answer)')}) + len({S.WORDS.replace('text', 'any_value(gold)')})) ELSE 0 END, 6) AS f1 FROM qa LEFT JOIN pa ON pa.conv_id = qa.conv_id AND pa.turn = qa.turn LEFT JOIN pg ON pg.conv_id = pa.conv_id AND pg.turn = pa.turn AND pg.t = pa.t GROUP BY qa.conv_id, qa.turn"))
def w_answer_f1(spark, sf_dir):
    return answers.overlap_f1(pairs(spark, sf_dir), ("conv_id", "turn"))


@query(S.with_(_QA, f"SELECT conv_id, turn, array_to_string({S.WORDS.replace('text', 'answer')}, ' ') = array_to_string({S.WORDS.replace('text', 'gold')}, ' ') AS exact FROM qa"))
def w_answer_exact(spark, sf_dir):
    return answers.exact(pairs(spark, sf_dir), ("conv_id", "turn"))


_ENC = {"bytes": "strlen(w)", "chars": "length(w)", "trigrams": "ceil(length(w) / 3)"}
_FERT = f"""wc AS (SELECT lang, w, count(*) AS n FROM (SELECT lang, unnest({S.WORDS}) AS w FROM documents) GROUP BY ALL),
pc AS ({" UNION ALL ".join(f"SELECT '{k}' AS encoder, lang, n, greatest({e}, 1)::DOUBLE AS p FROM wc" for k, e in _ENC.items())}),
fert AS (SELECT encoder, lang, round(sum(p * n) / sum(n), 6) AS fertility, round(sum(CASE WHEN p >= 2 THEN n ELSE 0 END) / sum(n), 6) AS continued FROM pc GROUP BY ALL)"""
ENCODERS = {"bytes": subword.by_bytes, "chars": subword.by_chars, "trigrams": subword.by_trigrams}


@query(S.with_(_FERT, "SELECT * FROM fert"))
def w_fertility(spark, sf_dir):
    return subword.fertility(table(spark, sf_dir, "documents"), ENCODERS)


@query(S.with_(_FERT, "SELECT encoder, round(avg(fertility), 6) AS avg_fertility, max(fertility) AS max_fertility, round(avg(continued), 6) AS avg_continued, max(continued) AS max_continued FROM fert WHERE lang <> 'en' GROUP BY encoder"))
def w_fertility_summary(spark, sf_dir):
    return subword.summary(subword.fertility(table(spark, sf_dir, "documents"), ENCODERS))


@query()
def w_fertility_trained(spark, sf_dir):
    """Longest match with vocabularies of several sizes, and merges trained here."""
    docs = table(spark, sf_dir, "documents")
    enc = {f"greedy_{k}": subword.greedy(subword.vocabulary(docs, k)) for k in (256, 1024)}
    return subword.fertility(docs, enc | {"merges_200": subword.by_merges(subword.train_bpe(docs, 200))})


#: The regions as families, nations below them, customers' segments as languages; nations with even keys have their own tokenizer.
_NODES = """nodes AS (SELECT 'root' AS node, NULL::VARCHAR AS parent, NULL::VARCHAR AS script, NULL::VARCHAR AS tokenizer, 0::BIGINT AS size
    UNION ALL SELECT 'r' || r_regionkey, 'root', NULL, NULL, 0 FROM region UNION ALL SELECT 'n' || n_nationkey, 'r' || n_regionkey, NULL, NULL, 0 FROM nation
    UNION ALL SELECT 'n' || c_nationkey || '-' || c_mktsegment, 'n' || c_nationkey, left(c_mktsegment, 4), CASE WHEN c_nationkey % 2 = 0 AND c_mktsegment < 'G' THEN 't' || c_nationkey || left(c_mktsegment, 2) END, count(*) FROM customer GROUP BY c_nationkey, c_mktsegment)"""
_TREE = f"""{_NODES},
up AS (SELECT node AS spot, script, tokenizer, size FROM nodes WHERE tokenizer IS NOT NULL UNION ALL SELECT n.parent, up.script, up.tokenizer, up.size FROM up JOIN nodes n ON n.node = up.spot WHERE n.parent IS NOT NULL AND n.parent <> 'root'),
best AS (SELECT spot, script, tokenizer FROM up QUALIFY row_number() OVER (PARTITION BY spot, script ORDER BY size DESC, tokenizer DESC) = 1),
path AS (SELECT node, script, node AS spot, 0 AS steps FROM nodes WHERE script IS NOT NULL UNION ALL SELECT path.node, path.script, n.parent, steps + 1 FROM path JOIN nodes n ON n.node = path.spot WHERE n.parent IS NOT NULL AND n.parent <> 'root'),
got AS (SELECT path.node, path.spot, best.tokenizer FROM path JOIN best ON best.spot = path.spot AND best.script = path.script QUALIFY row_number() OVER (PARTITION BY path.node ORDER BY steps) = 1)"""


@query(S.with_(_TREE, "SELECT n.node, n.script, got.tokenizer, CASE WHEN got.spot = n.node THEN 'native' ELSE got.spot END AS via FROM nodes n LEFT JOIN got USING (node) WHERE n.script IS NOT NULL"))
def w_proxy_tokenizer(spark, sf_dir):
    s = F.lit
    region = table(spark, sf_dir, "region").select(F.concat(s("r"), "r_regionkey").alias("node"), s("root").alias("parent"), s(None).cast("string").alias("script"), s(None).cast("string").alias("tokenizer"), s(0).cast("long").alias("size"))
    nation = table(spark, sf_dir, "nation").select(F.concat(s("n"), "n_nationkey").alias("node"), F.concat(s("r"), "n_regionkey").alias("parent"), s(None).cast("string").alias("script"), s(None).cast("string").alias("tokenizer"), s(0).cast("long").alias("size"))
    c = table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("size"))
    own = F.when((F.col("c_nationkey") % 2 == 0) & (F.col("c_mktsegment") < "G"), F.concat(s("t"), "c_nationkey", F.left("c_mktsegment", s(2))))
    leaf = c.select(F.concat(s("n"), "c_nationkey", s("-"), "c_mktsegment").alias("node"), F.concat(s("n"), "c_nationkey").alias("parent"), F.left("c_mktsegment", s(4)).alias("script"), own.alias("tokenizer"), "size")
    root = spark.createDataFrame([("root", None, None, None, 0)], "node string, parent string, script string, tokenizer string, size long")
    return tree.assign(root.unionByName(region).unionByName(nation).unionByName(leaf))
