"""Rates by cluster size, weights, baselines; the ladder of steps; the flagship."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.io import table
from mlcurate.operators import rehydrate, reports, selection
from mlcurate.session import settle
from mlcurate.workloads import dedup as D
from mlcurate.workloads import filters as X
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

#: rt: filter rates by cluster size of the survivors of deduplication; wt: their weights.
_KEPT = f"""{D.CLUSTERS},
{S.RECIPE},
sv AS (SELECT c.doc_id, c.lang, c.cluster_size, k.keep FROM clusters c JOIN kept k USING (doc_id) WHERE c.keep)"""
RATES = f"""{_KEPT},
sn AS (SELECT lang, cluster_size, count(*) AS n FROM sv GROUP BY ALL),
ss AS (SELECT *, sum(n) OVER (PARTITION BY lang ORDER BY cluster_size DESC) / sum(n) OVER (PARTITION BY lang) <= 0.001 AS tail FROM sn),
bn AS (SELECT lang, cluster_size, CASE WHEN tail THEN min(cluster_size) FILTER (tail) OVER (PARTITION BY lang) ELSE cluster_size END AS size_bin FROM ss),
r0 AS (SELECT lang, size_bin, count(*) AS n, count(*) FILTER (NOT keep) AS removed FROM sv JOIN bn USING (lang, cluster_size) GROUP BY ALL),
rt AS (SELECT lang, size_bin, n, removed, round(removed / n, 9) AS rate, round(sum(removed) OVER (PARTITION BY lang) / sum(n) OVER (PARTITION BY lang), 9) AS global_rate FROM r0),
wt AS (SELECT *, round(CASE WHEN rate < global_rate THEN coalesce(1 + 9.0 * (global_rate - rate) / nullif(global_rate - min(rate) OVER (PARTITION BY lang), 0), 1) ELSE 1 END, 6)::DOUBLE AS weight FROM rt)"""


def survivors(spark, sf_dir):
    """(doc_id, lang, cluster_size, keep) of one document per cluster, with the recipe's decision."""
    m, cuts, stop = X.recipe(spark, sf_dir)
    keep = selection.apply(m, cuts, stop).select("doc_id", "keep")
    found = D.clusters(spark, sf_dir).where("keep").select("doc_id", "lang", "cluster_size")
    return settle(found.join(keep, "doc_id"), "survivors")


@query(S.with_(RATES, "SELECT lang, size_bin, n, removed, round(rate, 6) AS rate, round(global_rate, 6) AS global_rate FROM rt"))
def w_rehydrate_rates(spark, sf_dir):
    return rehydrate.rates(survivors(spark, sf_dir)).select("lang", "size_bin", "n", "removed", F.round("rate", 6).alias("rate"), F.round("global_rate", 6).alias("global_rate"))


@query(S.with_(RATES, "SELECT lang, size_bin, weight FROM wt"))
def w_rehydrate_weights(spark, sf_dir):
    return rehydrate.weights(rehydrate.rates(survivors(spark, sf_dir))).select("lang", "size_bin", "weight")


@query(S.with_(RATES, "SELECT sv.doc_id, sv.lang, weight, floor(weight + 0.5)::INT AS n_repeats FROM sv JOIN bn USING (lang, cluster_size) JOIN wt USING (lang, size_bin) WHERE keep"))
def w_rehydrate_apply(spark, sf_dir):
    s = survivors(spark, sf_dir)
    w = rehydrate.weights(rehydrate.rates(s))
    return rehydrate.apply(s.where("keep"), w, s).select("doc_id", "lang", "weight", "n_repeats")


@query(S.with_(D.CLUSTERS, "SELECT lang, cluster_size, CASE WHEN cluster_size BETWEEN 2 AND 5 THEN 3 WHEN cluster_size BETWEEN 5 AND 100 THEN 5 WHEN cluster_size BETWEEN 101 AND 1000 THEN 8 WHEN cluster_size > 1000 THEN 10 ELSE 1 END AS repeats, count(*) AS n FROM clusters WHERE keep GROUP BY ALL"))
def w_rehydrate_steps(spark, sf_dir):
    c = D.clusters(spark, sf_dir).where("keep")
    return c.groupBy("lang", "cluster_size", rehydrate.step_weight(F.col("cluster_size")).alias("repeats")).agg(F.count(F.lit(1)).alias("n"))


@query(S.with_(D.CLUSTERS, "SELECT lang, CASE WHEN cluster_size >= 9 THEN 9 WHEN cluster_size >= 5 THEN 5 WHEN cluster_size >= 3 THEN 3 WHEN cluster_size >= 2 THEN 2 ELSE 1 END AS size_range, count(*) AS n FROM clusters WHERE keep GROUP BY ALL"))
def w_rehydrate_ranges(spark, sf_dir):
    return rehydrate.range_split(D.clusters(spark, sf_dir).where("keep")).groupBy("lang", "size_range").agg(F.count(F.lit(1)).alias("n"))


def ladder_parts(spark, sf_dir):
    """Stage -> (doc_id, lang, n_repeats): all, deduplicated, filtered, rehydrated."""
    s = survivors(spark, sf_dir)
    w = rehydrate.weights(rehydrate.rates(s))
    one = F.lit(1).alias("n_repeats")
    return {
        "1 identified": table(spark, sf_dir, "documents").select("doc_id", "lang", one),
        "2 deduplicated": s.select("doc_id", "lang", one),
        "3 filtered": s.where("keep").select("doc_id", "lang", one),
        "4 rehydrated": rehydrate.apply(s.where("keep"), w, s).select("doc_id", "lang", "n_repeats"),
    }


@query(S.with_(RATES, """SELECT stage, lang, count(*) AS n_docs, sum(n_repeats)::BIGINT AS n_repeated, round(avg(quality), 6) AS good_share FROM (
    SELECT '1 identified' AS stage, doc_id, lang, 1 AS n_repeats FROM documents UNION ALL SELECT '2 deduplicated', doc_id, lang, 1 FROM sv UNION ALL SELECT '3 filtered', doc_id, lang, 1 FROM sv WHERE keep
    UNION ALL SELECT '4 rehydrated', sv.doc_id, sv.lang, floor(weight + 0.5)::INT FROM sv JOIN bn USING (lang, cluster_size) JOIN wt USING (lang, size_bin) WHERE keep) x LEFT JOIN labels USING (doc_id) GROUP BY ALL"""))
def w_ladder(spark, sf_dir):
    """Each step with all else fixed: documents, documents as repeated, and the share of good ones among the labelled."""
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    out = None
    for name, df in ladder_parts(spark, sf_dir).items():
        x = df.join(labels, "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("n_repeats").cast("long").alias("n_repeated"), F.round(F.avg("quality"), 6).alias("good_share")).select(F.lit(name).alias("stage"), "lang", "n_docs", "n_repeated", "good_share")
        out = x if out is None else out.unionByName(x)
    return out


_ENTROPY = f"""{RATES},
step AS (SELECT '1 identified' AS stage, doc_id, lang, 1 AS k FROM documents UNION ALL SELECT '2 deduplicated', doc_id, lang, 1 FROM sv UNION ALL SELECT '3 filtered', doc_id, lang, 1 FROM sv WHERE keep
    UNION ALL SELECT '4 rehydrated', sv.doc_id, sv.lang, floor(weight + 0.5)::INT FROM sv JOIN bn USING (lang, cluster_size) JOIN wt USING (lang, size_bin) WHERE keep),
hd AS ({S.CLEAN} AND doc_id % 5 = 0),
tk AS MATERIALIZED (SELECT doc_id, lang, unnest(w) AS w, unnest(range(len(w))) AS i FROM (SELECT doc_id, lang, {S.WORDS} AS w FROM documents)),
tr AS MATERIALIZED (SELECT stage, tk.*, k FROM step JOIN tk USING (doc_id, lang) WHERE doc_id NOT IN (SELECT doc_id FROM hd)
    UNION ALL SELECT s.stage || '*', tk.*, 1 FROM tk JOIN hd USING (doc_id, lang), (SELECT DISTINCT stage FROM step) s),
vo AS (SELECT stage, lang, w FROM tr WHERE stage NOT LIKE '%*' GROUP BY ALL HAVING sum(k) >= 2),
vs AS (SELECT stage, lang, count(*) AS v FROM vo GROUP BY ALL),
sq AS (SELECT tr.stage, tr.lang, doc_id, i, k, CASE WHEN vo.w IS NULL THEN '<>' ELSE vo.w END AS w FROM tr LEFT JOIN vo ON vo.stage = rtrim(tr.stage, '*') AND vo.lang = tr.lang AND vo.w = tr.w),
bg AS (SELECT stage, lang, u, w, sum(k) AS c FROM (SELECT *, lag(w) OVER (PARTITION BY stage, lang, doc_id ORDER BY i) AS u FROM sq) WHERE u IS NOT NULL GROUP BY ALL),
un AS (SELECT stage, lang, u, sum(c) AS c FROM bg GROUP BY ALL)"""


@query(S.with_(_ENTROPY, """SELECT vs.stage, vs.lang, sum(h.c)::BIGINT AS n_bigrams, round(-sum(h.c * ln((coalesce(bg.c, 0) + 0.1) / (coalesce(un.c, 0) + 0.1 * (v + 1)))) / sum(h.c), 6) AS cross_entropy
    FROM bg h JOIN vs ON h.stage = vs.stage || '*' AND h.lang = vs.lang LEFT JOIN bg ON bg.stage = vs.stage AND bg.lang = h.lang AND bg.u = h.u AND bg.w = h.w LEFT JOIN un ON un.stage = vs.stage AND un.lang = h.lang AND un.u = h.u GROUP BY ALL"""))
def w_ladder_entropy(spark, sf_dir):
    """Bigram cross-entropy of held-out clean documents under each step's documents, as often as the step repeats them."""
    docs = table(spark, sf_dir, "documents")
    held = X.clean(spark, sf_dir).where("doc_id % 5 = 0").select("doc_id", "lang", "text")
    parts = ladder_parts(spark, sf_dir)
    times = {name: f"n{i}" for i, name in enumerate(parts)}
    each = [df.select("doc_id", *[(F.col("n_repeats") if n == name else F.lit(0)).cast("long").alias(c) for n, c in times.items()]) for name, df in parts.items()]
    steps = settle(reduce(DataFrame.union, each).groupBy("doc_id").agg(*[F.sum(c).alias(c) for c in times.values()]), "steps")
    train = docs.select("doc_id", "lang", "text").join(steps, "doc_id").join(held.select("doc_id"), "doc_id", "left_anti")
    out = reports.bigram_entropies(train, held, times)
    return out.withColumnRenamed("step", "stage")


def flagship(spark, sf_dir):
    """Per language: documents in, deduplicated, kept by the recipe, and as rehydrated."""
    s = survivors(spark, sf_dir)
    w = rehydrate.weights(rehydrate.rates(s))
    done = rehydrate.apply(s, w, s)
    n = table(spark, sf_dir, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("docs_in"))
    x = done.groupBy("lang").agg(F.count(F.lit(1)).alias("docs_dedup"), F.count_if("keep").alias("docs_kept"), F.sum(F.when(F.col("keep"), F.col("n_repeats")).otherwise(0)).cast("long").alias("docs_rehydrated"))
    return n.join(x, "lang", "left")


query(S.with_(RATES, """SELECT d.lang, d.n AS docs_in, x.a AS docs_dedup, x.b AS docs_kept, x.c AS docs_rehydrated FROM (SELECT lang, count(*) AS n FROM documents GROUP BY lang) d
    LEFT JOIN (SELECT lang, count(*) AS a, count(*) FILTER (keep) AS b, sum(CASE WHEN keep THEN floor(weight + 0.5)::INT ELSE 0 END)::BIGINT AS c FROM sv JOIN bn USING (lang, cluster_size) JOIN wt USING (lang, size_bin) GROUP BY lang) x USING (lang)"""), "w_flagship")(flagship)
