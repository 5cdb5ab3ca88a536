"""License scans: phrases, and an exact set-similarity join of text blocks with license templates.

Words are runs of digits, ASCII letters (case ignored) and non-ASCII characters.
A block is a window of ``BLOCK`` words of the whole text, begun every ``BLOCK // 2`` words;
line breaks are gaps like any other, so a notice may be wrapped. A block meets a template
if it holds at least ``THETA`` of the template's distinct words.
The template words are put in order of their frequency over all documents, rarest
first; a block that meets a template must hold one of its first few words (prefix
filter), have words enough (length filter), and have enough words left after the
place where they first meet (positional filter). What passes is verified exactly.

Defined cases: null and empty texts have no words, places or labels; rows that repeat
a doc_id and text share their labels; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Short standard notices by label.
TEMPLATES = [
    ("apache", "licensed under the apache license version 2 0"),
    ("apache", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis"),
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("gpl", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
]
THETA, BLOCK = 0.8, 64
_GAP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def spaced(text: Column) -> Column:
    """Words of a text with single spaces around each; case is kept."""
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), _GAP, " ")), F.lit(" "))


def _n_words(piece: Column) -> Column:
    t = F.trim(piece)
    return F.when(t == "", 0).otherwise(F.length(t) - F.length(F.replace(t, F.lit(" "), F.lit(""))) + 1).cast("long")


def _ascii_lower(c: Column) -> Column:
    return F.translate(c, _UPPER, _LOWER)


def phrases(docs: DataFrame) -> DataFrame:
    """doc_id, key, text and the base findings."""
    df = docs.select(F.col("doc_id").cast("long"), "text").withColumn("w", spaced(F.col("text")))
    df = df.withColumns({"n_words": _n_words(F.col("w")), "key": F.xxhash64("text"), "hit": F.col("w").rlike("(?i) (?:" + "|".join(PHRASES) + ") ")})
    cuts = {f"__{i}": F.when(F.col("hit"), F.split("w", f"(?i) (?={p} )", -1)).otherwise(F.array().cast("array<string>")) for i, p in enumerate(PHRASES)}
    df = df.withColumns(cuts)
    n = [F.greatest(F.size(c) - 1, F.lit(0)).cast("long") for c in cuts]
    first = [F.when(k > 0, _n_words(F.get(F.col(c), F.lit(0)))) for c, k in zip(cuts, n, strict=True)]
    last = [F.when(k > 0, F.col("n_words") - _n_words(F.element_at(F.col(c), -1))) for c, k in zip(cuts, n, strict=True)]
    labels = F.filter(F.array(*[F.when(k > 0, F.lit(x)) for k, x in zip(n, PHRASES.values(), strict=True)]), lambda x: x.isNotNull())
    return df.select("doc_id", "key", "n_words", sum(n[1:], n[0]).alias("n_base"), F.least(*first).alias("first_word"), F.greatest(*last).alias("last_word"), labels.alias("base"))


def frequencies(docs: DataFrame, words: list[str]) -> dict[str, int]:
    """How often each of a few words stands in all documents."""
    w = F.broadcast(docs.sparkSession.createDataFrame([(x,) for x in words], "word string"))
    every = docs.select(F.explode(F.split(F.trim(spaced(F.col("text"))), " ")).alias("word"))
    every = every.where(F.length("word") <= max(map(len, words))).select(F.lower("word").alias("word"))
    return {r.word: r.n for r in every.join(w, "word", "left_semi").groupBy("word").agg(F.count(F.lit(1)).alias("n")).collect()}


def blocks(docs: DataFrame, some: list[str]) -> DataFrame:
    """(doc_id, key, words) of the blocks that hold one of a few words."""
    seen = r"(?i)(?<![0-9a-z])(?:" + "|".join(sorted(some)) + r")(?![0-9a-z])"
    texts = docs.where(F.col("text").rlike(seen)).select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("key"), _ascii_lower(spaced(F.col("text"))).alias("t"))
    words = texts.select("doc_id", "key", F.split(F.trim("t"), " ").alias("w"))
    at = F.sequence(F.lit(0), F.greatest(F.size("w") - BLOCK // 2 - 1, F.lit(0)), F.lit(BLOCK // 2))
    x = words.select("doc_id", "key", F.explode(F.transform(at, lambda i: F.slice(F.col("w"), i + 1, F.lit(BLOCK)))).alias("words"))
    return x.where(F.arrays_overlap("words", F.array(*map(F.lit, sorted(some)))))


def similar(docs: DataFrame, templates=TEMPLATES, theta: float = THETA) -> DataFrame:
    """(doc_id, key, label, containment): every block and template that meet."""
    spark = docs.sparkSession
    vocab = sorted({w for _, t in templates for w in t.split()})
    freq = frequencies(docs, vocab)
    order = sorted(vocab, key=lambda w: (freq.get(w, 0), w))
    rank = {w: i for i, w in enumerate(order)}
    rows, prefix = [], []
    for k, (label, t) in enumerate(templates):
        own = sorted(set(t.split()), key=rank.__getitem__)
        need = math.ceil(theta * len(own) - 1e-9)
        rows.append((k, label, own, need))
        prefix += [(w, k, i, len(own), need) for i, w in enumerate(own[: len(own) - need + 1])]
    small = F.broadcast(spark.createDataFrame(prefix, "word string, template int, i int, n int, need int"))
    full = F.broadcast(spark.createDataFrame(rows, "template int, label string, own array<string>, need_all int"))
    b = blocks(docs, sorted({p[0] for p in prefix})).select("doc_id", "key", F.array_intersect(F.array(*map(F.lit, order)), "words").alias("known"))
    b = b.where(F.size("known") >= min(r[3] for r in rows)).select("doc_id", "key", "known", F.size("known").alias("nb"), F.posexplode("known").alias("j", "word"))
    met = b.join(small, "word").where((F.col("nb") >= F.col("need")) & (F.least(F.col("n") - F.col("i"), F.col("nb") - F.col("j")) + F.least("i", "j") >= F.col("need")))
    shared = F.size(F.array_intersect("known", "own"))
    return met.join(full, "template").where(shared >= F.col("need_all")).groupBy("doc_id", "key", "label").agg(F.max(shared / F.size("own")).alias("containment"))


def scan(docs: DataFrame) -> DataFrame:
    """Per document: words, places of the phrases, labels, and the best containment (1 where a phrase stands)."""
    found = similar(docs).groupBy("doc_id", "key").agg(F.collect_set("label").alias("more"), F.max("containment").alias("best"))
    df = phrases(docs).join(found.withColumnsRenamed({"doc_id": "d", "key": "k"}), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k")), "left")
    none = F.array().cast("array<string>")
    return df.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word",
        F.array_join(F.array_sort("base"), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base", F.coalesce("more", none))), ",").alias("labels"),
        F.when(F.col("n_base") > 0, 1.0).otherwise(F.round(F.coalesce("best", F.lit(0.0)), 6)).alias("score"),
    )
