"""Scores of tasks: rescaling, macro averages, smoothing, winners."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def rescale(score: Column, baseline: Column) -> Column:
    """Share of the way from a random baseline to a perfect score; 0 below the baseline."""
    return F.greatest(F.lit(0.0), (score - baseline) / (1 - baseline))


def macro(scores: DataFrame, by: tuple[str, ...] = ("model",), places: int = 6) -> DataFrame:
    """(by, category, score): mean of each category's tasks, and under category 'all' the mean of those means."""
    c = scores.groupBy(*by, "category").agg(F.avg("score").alias("score"))
    whole = c.groupBy(*by).agg(F.avg("score").alias("score")).withColumn("category", F.lit("all"))
    return c.unionByName(whole.select(c.columns)).withColumn("score", F.round("score", places))


def smooth(scores: DataFrame, width: int = 3, by: tuple[str, ...] = ("task", "model")) -> DataFrame:
    """``scores`` with ``smoothed``: mean of a step and those before it."""
    return scores.withColumn("smoothed", F.round(F.avg("score").over(Window.partitionBy(*by).orderBy("step").rowsBetween(1 - width, 0)), 6))


def winners(scores: DataFrame, by: str = "lang", who: str = "dataset") -> DataFrame:
    """(who, wins): in how many languages each has the best score; ties count for all."""
    r = scores.withColumn("r", F.rank().over(Window.partitionBy(by).orderBy(F.desc("score"))))
    return r.groupBy(who).agg(F.count_if(F.col("r") == 1).alias("wins"))
