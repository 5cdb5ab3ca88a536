"""Incremental ingest of crawl snapshots: fitted tables stay static, new documents stream past them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mlcurate.streaming.windows import apply_bounds

DOCUMENTS = "doc_id long, text string, lang string, source string, n_chars long"


def read(spark: SparkSession, path: str, files_per_trigger: int = 16) -> DataFrame:
    """A stream of the documents of snapshot files as they appear."""
    return spark.readStream.schema(DOCUMENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def distinct_texts(docs: DataFrame, ts: str = "arrived", wait: str = "10 days") -> DataFrame:
    """Exact copies that arrive within ``wait`` of each other go; state is one hash per text and expires."""
    x = docs.withColumn("h", F.sha2(F.coalesce("text", F.lit("")), 256))
    return x.withWatermark(ts, wait).dropDuplicatesWithinWatermark(["lang", "h"]).drop("h")


def flag(docs: DataFrame, cuts: DataFrame) -> DataFrame:
    """Join a stream of predictions (label, conf) with static cuts (label, cut)."""
    return docs.join(F.broadcast(cuts), "label", "left").withColumn("keep", F.col("conf") >= F.coalesce("cut", F.lit(0.9)))


def run(spark: SparkSession, source: str, sink: str, checkpoint: str, bounds: dict) -> None:
    """Filter what is there and append it to ``sink``; call again when more has come."""
    done = apply_bounds(read(spark, source), bounds).writeStream.format("parquet").option("path", sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    done.awaitTermination()
