"""Windows over arrival time, and stateless filters; the same functions take batches and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.functions import words as W


def _late(df: DataFrame, ts: str, wait: str | None) -> DataFrame:
    return df.withWatermark(ts, wait) if wait and df.isStreaming else df


def tumbling(df: DataFrame, width: str, wait: str | None = "1 hour", ts: str = "ts") -> DataFrame:
    """(window_start, event_type, n, mean)."""
    return sliding(df, width, width, wait, ts)


def sliding(df: DataFrame, width: str, slide: str, wait: str | None = "1 hour", ts: str = "ts") -> DataFrame:
    x = _late(df, ts, wait).groupBy(F.window(ts, width, slide).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean"))
    return x.select(F.col("w.start").alias("window_start"), "event_type", "n", "mean")


def sessions(df: DataFrame, gap: str, wait: str | None = "1 hour", ts: str = "ts") -> DataFrame:
    """(user_id, session_start, n): runs of a user's events with gaps below ``gap``."""
    x = _late(df, ts, wait).groupBy("user_id", F.session_window(ts, gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return x.select("user_id", F.col("w.start").alias("session_start"), "n")


def apply_bounds(docs: DataFrame, bounds: dict[str, tuple[float | None, float | None]]) -> DataFrame:
    """(doc_id, lang, keep) by fitted bounds of word metrics; no state, so any trigger gives the same flags."""
    n = F.size(W.words(F.col("text")))
    value = {"n_words": n, "avg_word_len": F.length(F.array_join(W.words(F.col("text")), "")) / F.greatest(n, F.lit(1))}
    keep = F.lit(True)
    for k, (lo, hi) in bounds.items():
        keep = keep & (value[k] >= lo if lo is not None else F.lit(True)) & (value[k] <= hi if hi is not None else F.lit(True))
    return docs.select("doc_id", "lang", keep.alias("keep"))
