"""Scoring of answers: accuracy of the likeliest option under four normalisations, word F1, exact match."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.functions import words as W


def normalised(norm: str) -> Column:
    """Log probability of an option: 'raw', per 'char', per 'token', or above its unconditional one ('pmi')."""
    p = F.col("logprob")
    return {"raw": p, "char": p / F.nullif("n_chars", F.lit(0)), "token": p / F.nullif("n_tokens", F.lit(0)), "pmi": p - F.col("prior_logprob")}[norm]


def picked(choices: DataFrame, norm: str = "token") -> DataFrame:
    """(item, choice, gold, right): each item's likeliest option; ties go to the first."""
    best = choices.groupBy("item").agg(F.max_by("choice", F.struct(F.round(normalised(norm), 9), -F.col("choice"))).alias("choice"), F.min("gold").alias("gold"))
    return best.withColumn("right", F.col("choice") == F.col("gold"))


def accuracy(choices: DataFrame, norm: str = "token") -> DataFrame:
    return picked(choices, norm).agg(F.count(F.lit(1)).alias("n_items"), F.count_if("right").alias("n_right"), F.round(F.avg(F.col("right").cast("double")), 6).alias("accuracy"))


def overlap_f1(answers: DataFrame, key: tuple[str, ...] = ("item",)) -> DataFrame:
    """(key, f1): shared words (each as often as both have it) against the words of answer and gold; columns answer, gold."""
    count = lambda c: F.aggregate(c, F.lit(0), lambda a, x: a + 1)
    w = answers.select(*key, W.words(F.col("answer")).alias("p"), W.words(F.col("gold")).alias("g"))
    numbered = lambda c: F.transform(c, lambda x, i: F.concat(x, F.lit("#"), F.size(F.filter(F.slice(c, 1, i), lambda y: y == x)).cast("string")))
    shared = F.size(F.array_intersect(numbered(F.col("p")), numbered(F.col("g"))))
    total = count(F.col("p")) + count(F.col("g"))
    return w.select(*key, F.round(F.when(total > 0, 2 * shared / total).otherwise(0.0), 6).alias("f1"))


def exact(answers: DataFrame, key: tuple[str, ...] = ("item",)) -> DataFrame:
    """(key, exact): are answer and gold the same words?"""
    return answers.select(*key, (F.array_join(W.words(F.col("answer")), " ") == F.array_join(W.words(F.col("gold")), " ")).alias("exact"))
