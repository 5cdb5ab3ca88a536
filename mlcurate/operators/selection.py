"""Applying filters, and choosing among threshold methods by validity and average rank."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mlcurate.operators.metrics import FIXED, long
from mlcurate.operators.thresholds import adapt, beyond

#: The recipe that ranks best: group -> (method, reference).
RECIPE = {"LQ": ("tail", "wiki"), "DQ": ("quantile", "wiki"), "RP": ("mean_std", "cc")}
COMBOS = [("none", "-"), ("english", "-"), *((m, r) for r in ("cc", "wiki") for m in ("tail", "mean_std", "median_ratio", "quantile"))]


def all_cuts(refs: dict[str, DataFrame], combos=None) -> DataFrame:
    """(method, ref, lang, rule, grp, direction, threshold) of every combination; refs: metrics by reference name."""
    combos = combos or COMBOS
    parts = [adapt(m, refs["cc" if r == "-" else r]).select(F.lit(m).alias("method"), F.lit(r).alias("ref"), "lang", "rule", "grp", "direction", "threshold") for m, r in combos]
    return reduce(DataFrame.unionByName, parts)


def recipe_cuts(refs: dict[str, DataFrame], recipe=None) -> DataFrame:
    """(lang, rule, grp, direction, threshold) of one method per group."""
    parts = [adapt(m, refs[r]).where(F.col("grp") == g) for g, (m, r) in (recipe or RECIPE).items()]
    return reduce(DataFrame.unionByName, parts)


def decisions(metrics: DataFrame, cuts: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, lang, *keep, rule, grp, bad): what each tuned rule says of each document; cuts are a few rows per language."""
    return long(metrics).join(F.broadcast(cuts.select(*keep, "lang", "rule", "threshold")), ["lang", "rule"]).select("doc_id", "lang", *keep, "rule", "grp", F.coalesce(beyond(F.col("value"), F.col("direction"), F.col("threshold")), F.lit(False)).alias("bad"))


def removal(metrics: DataFrame, cuts: DataFrame) -> DataFrame:
    """(grp, method, ref, lang, removed, worst): share of documents that a group removes, and that its worst single rule removes."""
    d = decisions(metrics, cuts, ("method", "ref"))
    by = ["grp", "method", "ref", "lang"]
    group = d.groupBy("doc_id", *by).agg(F.max("bad").alias("bad")).groupBy(*by).agg(F.round(F.avg(F.col("bad").cast("double")), 6).alias("removed"))
    rule = d.groupBy(*by, "rule").agg(F.avg(F.col("bad").cast("double")).alias("x")).groupBy(*by).agg(F.round(F.max("x"), 6).alias("worst"))
    return group.join(rule, by)


def valid(rates: DataFrame, cuts: DataFrame, most: float = 0.75) -> DataFrame:
    """(grp, method, ref, valid): no rule removes too much anywhere, something is removed, and every cut is defined. No filtering is always valid."""
    defined = cuts.groupBy("grp", "method", "ref").agg((F.count_if(F.col("threshold").isNull()) == 0).alias("defined"))
    x = rates.groupBy("grp", "method", "ref").agg(F.max("worst").alias("worst"), F.max("removed").alias("removed")).join(defined, ["grp", "method", "ref"])
    ok = (F.col("worst") <= most) & (F.col("removed") > 0) & F.col("defined")
    return x.select("grp", "method", "ref", (ok | (F.col("method") == "none")).alias("valid"))


def label_scores(metrics: DataFrame, cuts: DataFrame, labels: DataFrame) -> DataFrame:
    """(grp, method, ref, lang, score): F1 of removing documents of bad labelled quality; stands in for training a model on what is kept."""
    d = decisions(metrics.join(labels.select("doc_id"), "doc_id", "left_semi"), cuts, ("method", "ref"))
    by = ["grp", "method", "ref", "lang"]
    doc = d.groupBy("doc_id", *by).agg(F.max("bad").alias("bad")).join(labels.select("doc_id", (F.col("quality") == 0).alias("low")), "doc_id")
    tp, fp, fn = F.count_if(F.expr("bad and low")), F.count_if(F.expr("bad and not low")), F.count_if(F.expr("low and not bad"))
    return doc.groupBy(*by).agg(F.round(F.when(tp + fp + fn > 0, 2 * tp / (2 * tp + fp + fn)).otherwise(0.0), 6).alias("score"))


def rank(scores: DataFrame, ok: DataFrame) -> DataFrame:
    """(grp, method, ref, avg_rank): rank among valid combinations within language and group, averaged over languages."""
    s = scores.join(ok.where("valid"), ["grp", "method", "ref"])
    r = s.withColumn("r", F.rank().over(Window.partitionBy("grp", "lang").orderBy(F.desc("score"))))
    return r.groupBy("grp", "method", "ref").agg(F.round(F.avg("r"), 6).alias("avg_rank"))


def choose(ranks: DataFrame) -> DataFrame:
    """The combination with the best average rank of each group; ties by name."""
    return ranks.groupBy("grp").agg(F.min(F.struct("avg_rank", "method", "ref")).alias("x")).select("grp", "x.method", "x.ref", "x.avg_rank")


def apply(metrics: DataFrame, cuts: DataFrame, stop_hits: DataFrame | None = None, min_stop: int = 2, groups: tuple[str, ...] = ("LQ", "DQ", "RP"), fixed: bool = True) -> DataFrame:
    """(doc_id, lang, keep, reasons): flags on the narrow table; thresholds of a language ride along as one map, no shuffle."""
    own = cuts.where(F.col("grp").isin(list(groups))).groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("rule", "threshold"))).alias("__cut"))
    df = metrics.join(F.broadcast(own), "lang", "left")
    from mlcurate.operators.metrics import RULES

    tests = []
    for rule, (g, m, d, t) in {**(FIXED if fixed else {}), **RULES}.items():
        if g in groups:
            cut = F.lit(float(t)) if rule in FIXED else F.get(F.array(F.element_at("__cut", rule)), 0)
            tests.append(F.when(beyond(F.col(m).cast("double"), F.lit(d), cut), F.lit(rule)))
    if stop_hits is not None and fixed and "DQ" in groups:
        df = df.join(stop_hits.select("doc_id", "n_stopwords"), "doc_id", "left")
        tests.append(F.when(F.coalesce("n_stopwords", F.lit(0)) < min_stop, F.lit("F8")))
    reasons = F.array_sort(F.filter(F.array(*tests), lambda x: x.isNotNull())) if tests else F.array().cast("array<string>")
    return df.select("doc_id", "lang", reasons.alias("reasons")).select("doc_id", "lang", (F.size("reasons") == 0).alias("keep"), "reasons")
