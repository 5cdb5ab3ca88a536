"""Words of a text, per script; tokenizers are registered by name and may be a user's own."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{M}\p{N}]+"
ALL = r"[\p{L}\p{M}\p{N}]+|[^\s\p{L}\p{M}\p{N}]+"
#: Scripts written without spaces, by their codes: characters, or their pairs, stand for words.
UNSPACED = {"Hani": "Han", "Hira": "Hiragana", "Kana": "Katakana", "Thai": "Thai", "Khmr": "Khmer", "Laoo": "Lao", "Mymr": "Myanmar", "Tibt": "Tibetan"}
_ALONE = rf"([{''.join(rf'\p{{Is{x}}}' for x in UNSPACED.values())}]\p{{M}}*)"


def words(text: Column) -> Column:
    """Lower-cased runs of letters, marks and digits."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(WORD), F.lit(0))


def tokens(text: Column) -> Column:
    """``words`` and, between them, runs of other characters that aren't spaces."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(ALL), F.lit(0))


def whitespace(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(r"\S+"), F.lit(0))


def characters(text: Column) -> Column:
    """Each letter, mark or digit; for scripts without spaces."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"[\p{L}\p{N}]\p{M}*"), F.lit(0))


def _apart(text: Column) -> Column:
    """Text with spaces around every character of an unspaced script."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), _ALONE, " $1 ")


def unspaced(text: Column) -> Column:
    """Characters of unspaced scripts, one by one, and the words of other scripts between them."""
    return words(_apart(text))


def bigrams(text: Column) -> Column:
    """Overlapping pairs of characters; a single one stays alone."""
    c = characters(text)
    pair = lambda i: F.array_join(F.slice(c, i, F.lit(2)), "")
    return F.when(F.size(c) < 2, c).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(c) - 1, F.lit(1))), pair))


def longest_match(lexicon: list[str]) -> Callable[[Column], Column]:
    """Longest-match segmentation with a word list, as one alternation tried longest first; what it lacks is cut into characters."""
    import re

    known = "|".join(map(re.escape, sorted({w.lower() for w in lexicon}, key=lambda w: (-len(w), w))))
    return lambda text: F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(rf"(?:{known})|[\p{{L}}\p{{N}}]\p{{M}}*"), F.lit(0))


_REGISTRY: dict[str, Callable[[Column], Column]] = {"unicode": words, "all": tokens, "whitespace": whitespace, "cjk_char": characters, "cjk_bigram": bigrams, "unspaced": unspaced}
#: Tokenizers of languages whose words aren't runs of letters; a label may carry its script ("cmn_Hani").
BY_LANGUAGE = {x: "unspaced" for x in "zh cmn yue wuu nan hak gan lzh ja jpn th tha lo lao km khm my mya bo bod dz dzo shn".split()}


def register(name: str, fn: Callable[[Column], Column]) -> None:
    """Add a tokenizer: a function from a text column to an array of words."""
    _REGISTRY[name] = fn


def tokenizer(name: str) -> Callable[[Column], Column]:
    return _REGISTRY[name]


def assign(lang: str, name: str) -> None:
    """Use a registered tokenizer for a language wherever words are cut by language."""
    if name not in _REGISTRY:
        raise KeyError(name)
    BY_LANGUAGE[lang] = name


def _choose(lang: Column | None, plain: Column, other: Callable[[str], Column]) -> Column:
    """``plain`` but for the languages that have a tokenizer of their own; only the chosen branch is computed for a row."""
    if lang is None:
        return plain
    base = F.substring_index(lang, "_", 1)
    case = None
    for name in sorted(set(BY_LANGUAGE.values())):
        own = base.isin(sorted(x for x, n in BY_LANGUAGE.items() if n == name))
        case = F.when(own, other(name)) if case is None else case.when(own, other(name))
    return plain if case is None else case.otherwise(plain)


def words_in(text: Column, lang: Column | None = None) -> Column:
    """Words by the tokenizer of each row's language; without a language, ``words``."""
    return _choose(lang, words(text), lambda name: _REGISTRY[name](text))


def tokens_in(text: Column, lang: Column | None = None) -> Column:
    """``words_in`` and the runs of other characters between them; a user's own tokenizer decides alone what it gives."""
    return _choose(lang, tokens(text), lambda name: tokens(_apart(text)) if name == "unspaced" else _REGISTRY[name](text))


def language_of(df: DataFrame, by: str = "lang") -> Column | None:
    """The language column of ``df`` if it has one."""
    return F.col(by) if by in df.columns else None


def tokenize(df: DataFrame, text: str = "text", by: str | None = None, name: str = "unicode") -> DataFrame:
    """``df`` with array column ``words``; ``by`` names a column with each row's tokenizer."""
    if not by:
        return df.withColumn("words", _REGISTRY[name](F.col(text)))
    out = F.lit(None).cast("array<string>")
    for k, fn in _REGISTRY.items():
        out = F.when(F.col(by) == k, fn(F.col(text))).otherwise(out)
    return df.withColumn("words", out)


def lines(text: Column) -> Column:
    """Trimmed lines that aren't empty."""
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.trim(x)), lambda x: x != "")


def ngrams(w: Column, n: int) -> Column:
    """Word n-grams joined by spaces; a shorter text is one n-gram, an empty one none."""
    at = F.sequence(F.lit(1), F.greatest(F.size(w) - (n - 1), F.lit(1)))
    return F.when(F.size(w) == 0, F.array().cast("array<string>")).otherwise(F.transform(at, lambda i: F.array_join(F.slice(w, i, F.lit(n)), " ")))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` computed once; keeps generators from repeating an expensive expression per element."""
    return F.get(F.transform(F.array(value), body), 0)
