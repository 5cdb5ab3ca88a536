"""Queries and SQL of this subpackage; every query runs over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from mlcurate.io import table
from mlcurate.llm import oracles


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import jaccard_join

    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import token_counts as t

    return t.suffix_sums(t.histogram(t.encoded_lengths(table(spark, sf_dir, "documents"))))


def op3_token_id_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import id_files as f

    path = f.new_path(spark)
    f.write(table(spark, sf_dir, "documents"), path)
    return f.digest(spark, path)


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import line_dedup

    return line_dedup.report(table(spark, sf_dir, "documents"))


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import bpe

    return bpe.encode(table(spark, sf_dir, "documents"), digests=True)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import pii

    return pii.digest(table(spark, sf_dir, "documents"))


def op7_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import licenses

    return licenses.scan(table(spark, sf_dir, "documents"))


def op8_gif(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import gif

    return gif.digest(table(spark, sf_dir, "documents"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import decontaminate

    return decontaminate.search(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from mlcurate.llm import toxicity

    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def llm_pii_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of op6_pii that SQL can express."""
    return op6_pii(spark, sf_dir).drop("spans", "top_score")


QUERIES = {f.__name__: f for f in (op1_jaccard_join, op2_token_counts, op3_token_id_files, op4_line_dedup, op5_bpe, op6_pii, op7_licenses, op8_gif, op9_decontamination, op10_toxicity, llm_pii_base)}
ORACLES = {"op1_jaccard_join": oracles.JACCARD, "op7_licenses": oracles.LICENSES, "llm_pii_base": oracles.PII_BASE}
