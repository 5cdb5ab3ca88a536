"""Sources and sinks. Every reader takes an explicit or stored schema; nothing is inferred from text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_snapshot(df: DataFrame, expr: Column) -> DataFrame:
    """Add the crawl-snapshot label."""
    return df.withColumn("snapshot", expr)


def read_jsonl(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: str, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).csv(path, header=header)


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path).select(F.col("value").alias("text"))


def read_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def write_by_label(df: DataFrame, path: str, label: str = "lang", max_records: int = 1_000_000) -> None:
    """Parquet, one folder per label; rows of one label are spread by hash so that a dominant label has many writers."""
    df.repartition(F.col(label), F.pmod(F.xxhash64(*[F.col(c) for c in df.columns]), F.lit(32))).write.mode("overwrite").option("maxRecordsPerFile", max_records).partitionBy(label).parquet(path)


def write_jsonl(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("compression", "gzip").json(path)


def write_noop(df: DataFrame) -> None:
    """Run the plan and keep nothing; for benches."""
    df.write.format("noop").mode("overwrite").save()
