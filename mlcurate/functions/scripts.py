"""Dominant script of a text, and language labels with scripts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Script codes and the names that expressions know them by, in order of preference on ties.
SCRIPTS = {"Latn": "Latin", "Cyrl": "Cyrillic", "Arab": "Arabic", "Hani": "Han", "Thai": "Thai", "Deva": "Devanagari", "Telu": "Telugu", "Grek": "Greek", "Hebr": "Hebrew", "Hira": "Hiragana", "Kana": "Katakana", "Hang": "Hangul"}
#: Three-letter codes of two-letter language codes.
LONG = {"en": "eng", "de": "deu", "fr": "fra", "es": "spa"}


def dominant(text: Column) -> Column:
    """Script with the most letters; 'Zyyy' without any letter of a known one."""
    n = [F.struct(F.regexp_count(F.coalesce(text, F.lit("")), F.lit(rf"\p{{Is{name}}}")).alias("n"), F.lit(-i).alias("i"), F.lit(code).alias("s")) for i, (code, name) in enumerate(SCRIPTS.items())]
    best = F.array_max(F.array(*n))
    return F.when(best["n"] > 0, best["s"]).otherwise(F.lit("Zyyy"))


def label(lang: Column, script: Column) -> Column:
    """``xxx_Yyyy``."""
    long = F.coalesce(*[F.when(lang == k, F.lit(v)) for k, v in LONG.items()], lang)
    return F.concat(long, F.lit("_"), script)
