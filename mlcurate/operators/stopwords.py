"""Stopwords by frequency, reference cleaning, and word-frequency tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mlcurate.functions import scripts
from mlcurate.functions import words as W

#: Words of the fixed English list that the language-blind baseline uses for every language.
ENGLISH = ("the", "be", "to", "of", "and", "that", "have", "with")


def counts(docs: DataFrame, by: str = "lang") -> DataFrame:
    """(by, token, n): combined before the shuffle."""
    return docs.select(by, F.explode(W.words_in(F.col("text"), F.col(by))).alias("token")).groupBy(by, "token").agg(F.count(F.lit(1)).alias("n"))


def _frequencies(docs: DataFrame, by: str) -> DataFrame:
    """Words with a letter, and their share of all words of the language."""
    c = counts(docs, by)
    total = c.groupBy(by).agg(F.sum("n").alias("total"))
    return c.join(total, by).where(F.col("token").rlike(r"^[\p{L}\p{M}]+$")).select(by, "token", "n", (F.col("n") / F.col("total")).alias("freq"))


def _top(df: DataFrame, by: str, k: int) -> DataFrame:
    """The ``k`` most frequent words of each language. Each part first keeps its own best, so no task sees a whole vocabulary."""
    order = [F.desc("n"), F.asc("token")]
    first = Window.partitionBy(by, F.pmod(F.xxhash64("token"), F.lit(64))).orderBy(*order)
    few = df.withColumn("__r", F.row_number().over(first)).where(F.col("__r") <= k).drop("__r")
    return few.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(*order))).where(F.col("rank") <= k)


def fit(ref: DataFrame, cut: float = 0.008, min_words: int = 8, by: str = "lang") -> DataFrame:
    """(by, token, n, freq): words above the frequency cut; at least ``min_words``, for which the cut is lowered."""
    f = _frequencies(ref, by)
    return f.where(F.col("freq") >= cut).unionByName(_top(f, by, min_words).drop("rank")).distinct()


def topk(ref: DataFrame, k: int = 8, by: str = "lang") -> DataFrame:
    """Baseline: a fixed number of words per language."""
    return _top(_frequencies(ref, by), by, k).drop("rank")


def english8(spark, langs: list[str], by: str = "lang") -> DataFrame:
    """Baseline: the same English words for every language."""
    return spark.createDataFrame([(x, w) for x in langs for w in ENGLISH], f"{by} string, token string")


def leakage(words: DataFrame, english: str = "en", by: str = "lang") -> DataFrame:
    """(by, n_words, n_english, leak): share of each list that is in the English one."""
    en = words.where(F.col(by) == english).select("token", F.lit(1).alias("hit"))
    return words.join(F.broadcast(en), "token", "left").groupBy(by).agg(F.count(F.lit(1)).alias("n_words"), F.sum(F.coalesce("hit", F.lit(0))).alias("n_english"), F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("leak"))


def hits(docs: DataFrame, stop: DataFrame, occurrences: bool = False, by: str = "lang", key: str = "doc_id") -> DataFrame:
    """(key, by, n_stopwords): distinct list words (or their occurrences) in each document; list lengths are small per language."""
    lists = stop.groupBy(by).agg(F.collect_set("token").alias("__stop"))
    w = docs.join(F.broadcast(lists), by, "left").withColumn("__w", W.words_in(F.col("text"), F.col(by)))
    none = F.array().cast("array<string>")
    known = F.coalesce("__stop", none)
    n = F.size(F.filter("__w", lambda x: F.array_contains(known, x))) if occurrences else F.size(F.array_intersect("__w", known))
    return w.select(key, by, n.cast("long").alias("n_stopwords"))


def cut_tail(text: Column, heads: list[str]) -> Column:
    """Text up to the first line that is one of the headings (notes, references); the whole text without one."""
    import re

    return F.regexp_replace(text, rf"(?s)(?:^|\n)(?:{'|'.join(map(re.escape, heads))})[ \t]*(?:\n.*)?$", "")


def clean_reference(ref: DataFrame, pred: DataFrame | None = None, heads: tuple[str, ...] = ("References", "Notes"), cut: float = 0.7, expected: str = "Latn", english: str = "en") -> DataFrame:
    """Reference articles without note sections, in the expected script, and not taken for English (pred: doc_id, label, conf)."""
    df = ref.withColumn("text", cut_tail(F.col("text"), list(heads))).where(scripts.dominant(F.col("text")) == expected)
    if pred is not None:
        bad = pred.where((F.col("label") == english) & (F.col("conf") > cut)).select("doc_id")
        own = df.where(F.col("lang") != english).join(bad, "doc_id", "left_anti")
        df = df.where(F.col("lang") == english).unionByName(own)
    return df


def resolve(clean: DataFrame, fallback: DataFrame, min_docs: int = 20, by: str = "lang") -> DataFrame:
    """The clean reference where a language has enough of it, else the fallback corpus."""
    enough = clean.groupBy(by).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_docs).select(by)
    return clean.join(F.broadcast(enough), by, "left_semi").unionByName(fallback.join(F.broadcast(enough), by, "left_anti"))
