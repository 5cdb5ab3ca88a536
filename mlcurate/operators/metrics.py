"""Per-document quality metrics, in one pass: line and word metrics as expressions, n-gram repetition in Arrow batches."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.functions import words as W
from mlcurate.session import prepare

#: Characters that end a sentence.
TERMINAL = ".!?…\"”»。！？؟।"
BULLETS = ("•", "‣", "-", "*", "▪", "●")
TOP, DUP = (2, 3, 4), (5, 6, 7, 8, 9, 10)
#: Places that values and thresholds are rounded to before they are compared.
PLACES = 9

#: rule -> (group, metric, direction, English threshold); the tuned rules.
RULES = {
    "F2": ("LQ", "nonpunct_line_ratio", "max", 0.88),
    "F3": ("LQ", "lines_per_word", "max", 0.3),
    "F9": ("DQ", "avg_word_len", "max", 10.0),
    "F10": ("DQ", "avg_word_len", "min", 3.0),
    "F11": ("DQ", "nonalpha_word_ratio", "max", 0.2),
    "F12": ("RP", "dup_line_ratio", "max", 0.30),
    **{f"F{11 + n}": ("RP", f"top_{n}gram_char_ratio", "max", t) for n, t in zip(TOP, (0.20, 0.18, 0.16), strict=True)},
    **{f"F{11 + n}": ("RP", f"dup_{n}gram_char_ratio", "max", t) for n, t in zip(DUP, (0.15, 0.14, 0.13, 0.12, 0.11, 0.10), strict=True)},
}
#: rule -> (group, metric, direction, bound); the fixed ones (F8, stopwords, is separate).
FIXED = {
    "F1": ("LQ", "dup_line_char_ratio", "max", 0.1),
    "F4a": ("DQ", "n_words", "min", 50.0),
    "F4b": ("DQ", "n_words", "max", 100_000.0),
    "F5": ("DQ", "symbol_word_ratio", "max", 0.1),
    "F6": ("DQ", "bullet_line_ratio", "max", 0.9),
    "F7": ("DQ", "ellipsis_line_ratio", "max", 0.3),
}


def line_metrics(df: DataFrame) -> DataFrame:
    """``df`` (text) with n_lines and the line ratios."""
    df = df.withColumn("__l", W.lines(F.col("text")))
    l, n = F.col("__l"), F.greatest(F.size("__l"), F.lit(1))
    chars = lambda a: F.length(F.array_join(a, ""))
    share = lambda test: F.size(F.filter(l, test)) / n
    df = df.withColumn("__d", F.array_distinct("__l"))
    return df.withColumns({
        "n_lines": F.size(l).cast("long"),
        "dup_line_ratio": (F.size(l) - F.size("__d")) / n,
        "dup_line_char_ratio": (chars(l) - chars(F.col("__d"))) / F.greatest(chars(l), F.lit(1)),
        "nonpunct_line_ratio": share(lambda x: ~F.right(x, F.lit(1)).isin(list(TERMINAL))),
        "bullet_line_ratio": share(lambda x: F.left(x, F.lit(1)).isin(list(BULLETS))),
        "ellipsis_line_ratio": share(lambda x: x.endswith("…") | x.endswith("...")),
    }).drop("__l", "__d")


def word_metrics(df: DataFrame) -> DataFrame:
    """``df`` (text, n_lines, lang if known) with word counts and ratios, words by the language's tokenizer."""
    lang = W.language_of(df)
    df = df.withColumns({"__w": W.words_in(F.col("text"), lang), "__t": W.tokens_in(F.col("text"), lang)})
    n = F.greatest(F.size("__w"), F.lit(1))
    return df.withColumns({
        "n_words": F.size("__w").cast("long"),
        "avg_word_len": F.length(F.array_join("__w", "")) / n,
        "lines_per_word": F.when(F.size("__w") > 0, F.col("n_lines") / n).otherwise(0.0),
        "symbol_word_ratio": F.regexp_count(F.coalesce("text", F.lit("")), F.lit(r"#|…|\.\.\.")) / n,
        "nonalpha_word_ratio": F.size(F.filter("__t", lambda x: ~x.rlike(r"\p{L}"))) / F.greatest(F.size("__t"), F.lit(1)),
    }).drop("__w", "__t")


def repetition(words: list[str]) -> list[float]:
    """Shares of the most frequent 2- to 4-grams and of what repeated 5- to 10-grams cover, by characters."""
    known: dict[str, int] = {}
    ids = np.fromiter((known.setdefault(w, len(known)) for w in words), np.int64, len(words))
    lens = np.fromiter(map(len, words), np.int64, len(words))
    total = max(int(lens.sum()), 1)
    ends = np.concatenate([[0], np.cumsum(lens)])
    out, gram = [], ids
    for n in range(2, max(DUP) + 1):
        k = len(ids) - n + 1
        if k < 1:
            out.append(0.0)
            continue
        # an n-gram is its (n-1)-gram and one word more; ranks keep numbers small and exact
        gram = np.unique(gram[:k] * (len(known) + 1) + ids[n - 1 :], return_inverse=True)[1]
        count = np.bincount(gram)
        if n in TOP:
            most = count.max()
            size = (ends[n:] - ends[:-n])[count[gram] == most].max()
            out.append(float(most * size / total) if most > 1 else 0.0)
        elif n in DUP:
            step = np.zeros(len(ids) + 1, np.int64)
            at = np.flatnonzero(count[gram] > 1)
            np.add.at(step, at, 1)
            np.add.at(step, at + n, -1)
            out.append(float(lens[np.cumsum(step[:-1]) > 0].sum() / total))
    return out


REPETITION = [*(f"top_{n}gram_char_ratio" for n in TOP), *(f"dup_{n}gram_char_ratio" for n in DUP)]


def repetition_metrics(df: DataFrame) -> DataFrame:
    """``df`` (text, lang if known) with the n-gram ratios; whole texts, one Arrow pass."""
    prepare(df.sparkSession)
    from pyspark.sql.types import DoubleType, StructType

    fields = df.withColumn("__w", W.words_in(F.col("text"), W.language_of(df)))

    def run(batches):
        import pyarrow as pa

        for b in batches:
            got = [repetition(x or []) for x in b.column(b.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *[pa.array([g[i] for g in got], pa.float64()) for i in range(len(REPETITION))]], [*b.schema.names[:-1], *REPETITION])

    schema = StructType(list(df.schema.fields))
    for c in REPETITION:
        schema = schema.add(c, DoubleType())
    return fields.mapInArrow(run, schema)


METRICS = ["n_lines", "dup_line_ratio", "dup_line_char_ratio", "nonpunct_line_ratio", "bullet_line_ratio", "ellipsis_line_ratio", "n_words", "avg_word_len", "lines_per_word", "symbol_word_ratio", "nonalpha_word_ratio", *REPETITION]


def compute(docs: DataFrame, keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """``keep`` columns and every metric, values rounded; the narrow side table that all filters work from."""
    df = word_metrics(line_metrics(repetition_metrics(docs.select(*keep, "text"))))
    return df.select(*keep, *[F.col(m) if m.startswith("n_") else F.round(m, PLACES).alias(m) for m in METRICS])


def long(metrics: DataFrame, rules=None, keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """A row per document and rule: rule, grp, metric, direction, t_en, value."""
    rules = rules or RULES
    rows = [F.struct(F.lit(r).alias("rule"), F.lit(g).alias("grp"), F.lit(m).alias("metric"), F.lit(d).alias("direction"), F.lit(float(t)).alias("t_en"), F.col(m).cast("double").alias("value")) for r, (g, m, d, t) in rules.items()]
    return metrics.select(*keep, F.explode(F.array(*rows)).alias("x")).select(*keep, "x.*")
