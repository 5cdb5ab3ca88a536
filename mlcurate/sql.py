"""The scalar methods for SQL users: functions and table functions registered in a session."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from mlcurate.session import prepare


@udtf(returnType="line string, pos int")
class TextLines:
    def eval(self, text: str):
        for i, x in enumerate((text or "").split("\n")):
            yield x, i


@udtf(returnType="domain string")
class DomainSuffixes:
    def eval(self, host: str):
        parts = (host or "").split(".")
        for i in range(len(parts)):
            yield (".".join(parts[i:]),)


@udtf(returnType="shingle string, pos int")
class Shingles:
    def eval(self, text: str, n: int):
        import re

        w = re.findall(r"[^\W_]+", (text or "").lower())
        for i in range(max(len(w) - n + 1, 1) if w else 0):
            yield " ".join(w[i : i + n]), i


def register(spark: SparkSession) -> None:
    """Table functions, and expressions as temporary SQL functions (no Python in those)."""
    prepare(spark)
    for name, f in (("text_lines", TextLines), ("domain_suffixes", DomainSuffixes), ("shingles", Shingles)):
        spark.udtf.register(name, f)
    for name, args, body in (
        ("corpus_words", "t STRING", r"regexp_extract_all(lower(coalesce(t, '')), r'[\p{L}\p{M}\p{N}]+', 0)"),
        ("rescale_score", "s DOUBLE, b DOUBLE", "greatest(0D, (s - b) / (1 - b))"),
        ("step_weight", "n BIGINT", "CASE WHEN n BETWEEN 2 AND 5 THEN 3 WHEN n BETWEEN 5 AND 100 THEN 5 WHEN n BETWEEN 101 AND 1000 THEN 8 WHEN n > 1000 THEN 10 ELSE 1 END"),
        ("crawl_precision", "x DOUBLE, r DOUBLE, f DOUBLE", "x * r / (x * r + (1 - x) * f)"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURN {body}")
