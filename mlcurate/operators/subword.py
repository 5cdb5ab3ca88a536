"""How well subword tokenizers fit languages: pieces per word, and words that are cut.

An encoder is a function from a word column to the number of its pieces, so any
tokenizer that can be said in expressions, or as an Arrow function, can be compared.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.functions import words as W
from mlcurate.session import prepare, settle

Encoder = Callable[[Column], Column]


def by_bytes(w: Column) -> Column:
    return F.octet_length(w)


def by_chars(w: Column) -> Column:
    return F.length(w)


def by_trigrams(w: Column) -> Column:
    return F.ceil(F.length(w) / 3).cast("int")


def greedy(vocab: list[str]) -> Encoder:
    """Longest match from the left with a vocabulary; characters it lacks are pieces of their own."""
    import re

    known = "|".join(map(re.escape, sorted(set(vocab), key=lambda x: (-len(x), x))))
    return lambda w: F.size(F.regexp_extract_all(w, F.lit(f"(?s)(?:{known})|."), F.lit(0)))


def by_merges(merges: list[tuple[str, str]]) -> Encoder:
    """Pieces by a trained list of merges, in Arrow batches."""
    rank = {p: i for i, p in enumerate(merges)}

    def pieces(word: str) -> int:
        s = list(word)
        while len(s) > 1:
            best = min(((rank.get(p, len(rank)), i) for i, p in enumerate(zip(s, s[1:], strict=False))), default=(len(rank), 0))
            if best[0] == len(rank):
                break
            i = best[1]
            s[i : i + 2] = [s[i] + s[i + 1]]
        return len(s)

    @F.pandas_udf("int")
    def count(w: pd.Series) -> pd.Series:
        known: dict[str, int] = {}
        return w.map(lambda x: known[x] if x in known else known.setdefault(x, pieces(x or "")))

    return count


def vocabulary(docs: DataFrame, size: int) -> list[str]:
    """The ``size`` most frequent words."""
    c = docs.select(F.explode(W.words(F.col("text"))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    return [r.w for r in c.orderBy(F.desc("n"), "w").limit(size).collect()]


def _merged(word: list[str], merges: list[tuple[str, str]]) -> list[str]:
    for a, b in merges:
        if a not in word or b not in word:
            continue
        s, i = [], 0
        while i < len(word):
            both = i + 1 < len(word) and word[i] == a and word[i + 1] == b
            s.append(a + b if both else word[i])
            i += 2 if both else 1
        word = s
    return word


def _safe(top: list[tuple[int, str, str]]) -> list[tuple[str, str]]:
    """The leading pairs that stay the best ones one after the other, whatever merging those before does to counts.

    A merge lowers only counts of pairs that share a symbol with it, and a new pair is no more frequent than the
    pair that shared a symbol before; so a pair is safe while no such pair is as frequent. The last of ``top`` bounds what isn't in it."""
    out: list[tuple[str, str]] = []
    used: set[str] = set()
    for n, a, b in top:
        touched = any(m >= n and (x, y) not in out and used & {x, y} for m, x, y in top)
        if out and (touched or n == top[-1][0]):
            break
        out.append((a, b))
        used |= {a, b}
        if a == b:
            break
    return out


def train_bpe(docs: DataFrame, merges: int, top: int = 100) -> list[tuple[str, str]]:
    """Merges of the most frequent pairs, on the counts of all words; only the ``top`` pairs of a round come to the driver."""
    prepare(docs.sparkSession)
    c = docs.select(F.explode(W.words(F.col("text"))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    words = settle(c.select(F.split("w", "").alias("w"), "n"), "words")
    out: list[tuple[str, str]] = []
    while len(out) < merges:
        pairs = words.select("n", F.explode(F.arrays_zip(F.slice("w", 1, F.size("w") - 1).alias("a"), F.slice("w", 2, F.size("w")).alias("b"))).alias("p")).groupBy("p.a", "p.b").agg(F.sum("n").alias("n"))
        best = [(r.n, r.a, r.b) for r in pairs.orderBy(F.desc("n"), "a", "b").limit(top).collect()]
        if not best:
            break
        new = _safe(best)[: merges - len(out)]
        out += new
        step = F.udf(lambda w, new=new: _merged(w, new), "array<string>")
        words = settle(words.select(step("w").alias("w"), "n"), "words")
    return out


def fertility(docs: DataFrame, encoders: dict[str, Encoder], by: str = "lang") -> DataFrame:
    """(encoder, by, fertility, continued): mean pieces per word, and share of words in two pieces or more.

    Words are counted once per language and encoded once each."""
    c = docs.select(by, F.explode(W.words(F.col("text"))).alias("w")).groupBy(by, "w").agg(F.count(F.lit(1)).alias("n"))
    wide = c.select(by, "n", *[e(F.col("w")).cast("double").alias(k) for k, e in encoders.items()])
    x = wide.select(by, "n", F.explode(F.array(*[F.struct(F.lit(k).alias("encoder"), F.greatest(F.col(k), F.lit(1.0)).alias("p")) for k in encoders])).alias("e")).select(by, "n", "e.*")
    return x.groupBy("encoder", by).agg(F.round(F.sum(F.col("p") * F.col("n")) / F.sum("n"), 6).alias("fertility"), F.round(F.sum(F.when(F.col("p") >= 2, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("continued"))


def summary(f: DataFrame, english: str = "en", by: str = "lang") -> DataFrame:
    """(encoder, mean and worst of both over languages other than English)."""
    x = f.where(F.col(by) != english).groupBy("encoder")
    return x.agg(F.round(F.avg("fertility"), 6).alias("avg_fertility"), F.max("fertility").alias("max_fertility"), F.round(F.avg("continued"), 6).alias("avg_continued"), F.max("continued").alias("max_continued"))


def screen(s: DataFrame, sizes: dict[str, int], lossless: dict[str, bool], most: int = 256_000, worst: float = 0.95) -> DataFrame:
    """``s`` with ``usable``: vocabulary small enough, nothing lost, and no language covered badly."""
    ok = F.lit(False)
    for k, n in sizes.items():
        ok = F.when(F.col("encoder") == k, F.lit(n <= most and lossless.get(k, True)) & (F.col("max_continued") <= worst)).otherwise(ok)
    return s.withColumn("usable", ok)
