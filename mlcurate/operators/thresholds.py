"""Thresholds of filters carried over from English to any language, by several rules.

Statistics of every metric come from one aggregation per reference corpus; the cuts
are arithmetic on them. The quantile rule needs a second aggregation whose
probabilities (one number per rule: the share that the English cut removes in
English) come to the driver first, since percentiles take literal probabilities only.
``accuracy`` switches exact percentiles for sketches at scale.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.operators.metrics import PLACES, RULES

METHODS = ("mean_std", "median_std", "quantile", "tail", "median_ratio")


def beyond(value: Column, direction: Column, cut: Column) -> Column:
    """Does a filter reject this value? Strictly beyond the cut."""
    return F.when(direction == "max", value > cut).otherwise(value < cut)


def percentile(value, p, accuracy: int | None = None) -> Column:
    return F.percentile_approx(value, p, accuracy).cast("double") if accuracy else F.percentile(value, p)


def stats(metrics: DataFrame, by: str = "lang", accuracy: int | None = None) -> DataFrame:
    """(by, rule, grp, direction, t_en, mean, med, std): one row per language and rule."""
    aggs = []
    for m in sorted({r[1] for r in RULES.values()}):
        aggs += [F.avg(m).alias(f"{m}__mean"), percentile(m, 0.5, accuracy).alias(f"{m}__med"), F.stddev_pop(m).alias(f"{m}__std")]
    wide = metrics.groupBy(by).agg(*aggs)
    rows = [F.struct(F.lit(r).alias("rule"), F.lit(g).alias("grp"), F.lit(d).alias("direction"), F.lit(float(t)).alias("t_en"), *[F.col(f"{m}__{s}").alias(s) for s in ("mean", "med", "std")]) for r, (g, m, d, t) in RULES.items()]
    return wide.select(by, F.explode(F.array(*rows)).alias("x")).select(by, "x.*")


def _rounded(df: DataFrame, cut: Column, by: str) -> DataFrame:
    return df.select(by, "rule", "grp", "direction", F.round(cut, PLACES).alias("threshold"))


def _with_english(s: DataFrame, by: str, english: str) -> DataFrame:
    """Statistics beside the English ones: one row per rule, so the broadcast never grows."""
    en = s.where(F.col(by) == english).select("rule", *[F.col(c).alias(f"en_{c}") for c in ("mean", "med", "std")])
    return s.join(F.broadcast(en), "rule")


def adapt(method: str, metrics: DataFrame, by: str = "lang", english: str = "en", p: float = 0.1, accuracy: int | None = None) -> DataFrame:
    """(by, rule, grp, direction, threshold); a null threshold means that the method is undefined there."""
    if method in ("quantile", "tail"):
        share = {r: p for r in RULES}
        if method == "quantile":
            en = metrics.where(F.col(by) == english)
            cuts = [F.avg((F.col(m) > t if d == "max" else F.col(m) < t).cast("double")).alias(r) for r, (_, m, d, t) in RULES.items()]
            share = en.agg(*cuts).first().asDict()  # one number per rule
        at = {r: None if share[r] is None else (1 - share[r] if d == "max" else share[r]) for r, (_, _, d, _) in RULES.items()}
        wide = metrics.groupBy(by).agg(*[(percentile(m, float(at[r]), accuracy) if at[r] is not None else F.lit(None).cast("double")).alias(r) for r, (_, m, _, _) in RULES.items()])
        rows = [F.struct(F.lit(r).alias("rule"), F.lit(g).alias("grp"), F.lit(d).alias("direction"), F.col(r).alias("c")) for r, (g, _, d, _) in RULES.items()]
        return _rounded(wide.select(by, F.explode(F.array(*rows)).alias("x")).select(by, "x.*"), F.col("c"), by)
    s = _with_english(stats(metrics, by, accuracy), by, english)
    if method == "english":
        return _rounded(s, F.col("t_en"), by)
    if method == "none":
        return _rounded(s, F.lit(None).cast("double"), by)
    some = F.when(F.col("en_std") > 0, F.col("std") * (F.col("t_en") - F.col("en_mean" if method == "mean_std" else "en_med")) / F.nullif("en_std", F.lit(0.0)))
    cut = {"mean_std": F.col("mean") + some, "median_std": F.col("med") + some, "median_ratio": F.when(F.col("en_med") != 0, F.col("t_en") * F.col("med") / F.nullif("en_med", F.lit(0.0)))}[method]
    return _rounded(s, cut, by)
