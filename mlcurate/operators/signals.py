"""Which evaluation tasks are informative: four statistics of score series, and the choice by them.

scores: task, model, step, score (and baseline); a series is a model's scores of a task by step.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def monotonicity(scores: DataFrame) -> DataFrame:
    """(task, monotonicity): mean over models of the rank correlation of step and score; null where a series is constant."""
    by = ["task", "model"]
    ranked = lambda c: F.rank().over(Window.partitionBy(*by).orderBy(c)) + (F.count(F.lit(1)).over(Window.partitionBy(*by, c)) - 1) / 2
    r = scores.select(*by, ranked("step").alias("x"), ranked("score").alias("y"))
    m = Window.partitionBy(*by)
    c = r.select(*by, (F.col("x") - F.avg("x").over(m)).alias("dx"), (F.col("y") - F.avg("y").over(m)).alias("dy"))
    rho = c.groupBy(*by).agg((F.sum(F.col("dx") * F.col("dy")) / F.nullif(F.sqrt(F.sum(F.col("dx") ** 2) * F.sum(F.col("dy") ** 2)), F.lit(0.0))).alias("rho"))
    return rho.groupBy("task").agg(F.round(F.avg("rho"), 6).alias("monotonicity"))


def snr(scores: DataFrame) -> DataFrame:
    """(task, snr): at each step, mean over seed models divided by their standard deviation; averaged over steps that vary."""
    s = scores.groupBy("task", "step").agg((F.avg("score") / F.nullif(F.stddev_pop("score"), F.lit(0.0))).alias("x"))
    return s.groupBy("task").agg(F.round(F.avg("x"), 6).alias("snr"))


def non_random(scores: DataFrame, last: int = 5) -> DataFrame:
    """(task, non_random): best final score above the baseline, in standard deviations over models, averaged over the last steps."""
    end = scores.groupBy("task", "model").agg(F.max_by("score", "step").alias("final"), F.first("baseline").alias("b")).groupBy("task").agg((F.max("final") - F.first("b")).alias("gain"))
    s = scores.groupBy("task", "step").agg(F.stddev_pop("score").alias("s")).withColumn("r", F.row_number().over(Window.partitionBy("task").orderBy(F.desc("step")))).where(F.col("r") <= last)
    spread = s.groupBy("task").agg(F.avg("s").alias("s"))
    return end.join(spread, "task").select("task", F.round(F.col("gain") / F.nullif("s", F.lit(0.0)), 6).alias("non_random"))


def ordering(scores: DataFrame, start: int) -> DataFrame:
    """(task, ordering): agreement of the models' order between consecutive steps from ``start`` on; ties count as neither."""
    w = Window.partitionBy("task", "model").orderBy("step")
    s = scores.select("task", "model", "step", "score", F.lag("score").over(w).alias("before")).where((F.col("step") >= start) & F.col("before").isNotNull())
    a, b = s.alias("a"), s.alias("b")
    pair = a.join(b, (F.col("a.task") == F.col("b.task")) & (F.col("a.step") == F.col("b.step")) & (F.col("a.model") < F.col("b.model")))
    sign = F.signum(F.col("a.score") - F.col("b.score")) * F.signum(F.col("a.before") - F.col("b.before"))
    t = pair.groupBy(F.col("a.task").alias("task"), F.col("a.step").alias("step")).agg(F.avg(sign).alias("tau"))
    return t.groupBy("task").agg(F.round(F.avg("tau"), 6).alias("ordering"))


def noise(scores: DataFrame) -> DataFrame:
    """(task, noise): standard deviation over models at the last step."""
    last = scores.withColumn("r", F.rank().over(Window.partitionBy("task").orderBy(F.desc("step")))).where("r = 1")
    return last.groupBy("task").agg(F.round(F.stddev_pop("score"), 6).alias("noise"))


def select(scores: DataFrame, generative: tuple[str, ...] = (), least_mono: float = 0.5, least_snr: float = 20.0, least_gain: float = 3.0) -> DataFrame:
    """(task, monotonicity, snr, non_random, selected); generative tasks need no signal-to-noise ratio."""
    x = monotonicity(scores).join(snr(scores), "task").join(non_random(scores), "task")
    ok = (F.col("monotonicity") >= least_mono) & ((F.col("snr") >= least_snr) | F.col("task").isin(list(generative))) & (F.col("non_random") >= least_gain)
    return x.withColumn("selected", F.coalesce(ok, F.lit(False)))
