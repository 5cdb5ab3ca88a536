"""Token counts: exact length histogram with suffix sums.

Documents are aggregated by encoded length; from the histogram alone, suffix sums
answer for every context limit how many documents reach it, how many tokens they
hold, and how many tokens remain if every document is cut at the limit.

Defined cases: null and empty texts have length 0 and count as documents; an empty
table gives an empty histogram; repeated rows count each time; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mlcurate.llm import tokens
from mlcurate.session import prepare, settle

#: Lengths that share one running sum; runs are then joined by their totals.
RUN = 1024


def encoded_lengths(docs: DataFrame, path: str | None = None, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``n_tokens`` of each whole text."""
    prepare(docs.sparkSession)
    path = path or tokens.default_path()
    schema = docs.select(*keep).schema

    def count(batches):
        import pyarrow as pa

        t = tokens.table(path)
        for b in batches:
            texts = b.column(b.num_columns - 1)
            for i, j in tokens.slices(texts):
                yield pa.RecordBatch.from_arrays([*[c[i:j] for c in b.columns[:-1]], pa.array(t.counts(texts[i:j]), pa.int64())], [*keep, "n_tokens"])

    from pyspark.sql.types import LongType, StructType

    out = StructType([*schema.fields]).add("n_tokens", LongType())
    return docs.select(*keep, F.col(text).alias("__text")).mapInArrow(count, out)


def histogram(lengths: DataFrame) -> DataFrame:
    """(n_tokens, n_docs), one row per distinct length; combined before the shuffle and written once, since the sums read it more than once."""
    return settle(lengths.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n_docs")), "lengths")


def suffix_sums(hist: DataFrame) -> DataFrame:
    """Per length: documents and tokens at or above it, and the total left when every document is cut at it.

    Sums run within runs of ``RUN`` lengths and over the runs' totals, so no task
    holds more than one run, or one row per run."""
    h = hist.select("n_tokens", "n_docs", (F.col("n_tokens") * F.col("n_docs")).alias("n_sum"), F.floor(F.col("n_tokens") / RUN).cast("long").alias("run"))
    down = Window.partitionBy("run").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    above = Window.orderBy(F.desc("run")).rowsBetween(Window.unboundedPreceding, -1)
    runs = h.groupBy("run").agg(F.sum("n_docs").alias("d"), F.sum("n_sum").alias("t"))
    runs = runs.select("run", F.coalesce(F.sum("d").over(above), F.lit(0)).alias("d_above"), F.coalesce(F.sum("t").over(above), F.lit(0)).alias("t_above"), F.sum("t").over(Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)).alias("t_below"))
    x = h.withColumns({"d_here": F.sum("n_docs").over(down), "t_here": F.sum("n_sum").over(down), "t_run": F.sum("n_sum").over(Window.partitionBy("run"))}).join(runs, "run")
    return x.select(
        "n_tokens", "n_docs",
        (F.col("d_here") + F.col("d_above")).alias("docs_from"),
        (F.col("t_here") + F.col("t_above")).alias("tokens_from"),
        (F.coalesce("t_below", F.lit(0)) + F.col("t_run") - F.col("t_here") + F.col("n_tokens") * (F.col("d_here") + F.col("d_above"))).alias("tokens_cut_here"),
    )


def at_limits(sums: DataFrame, limits: list[int]) -> DataFrame:
    """Answers for any context limits, also ones that no document has: (context, docs_over, tokens_total, tokens_kept)."""
    spark = sums.sparkSession
    want = spark.createDataFrame([(int(x),) for x in limits], "context long")
    total = sums.agg(F.max("tokens_from").alias("tokens_total"))
    # the first length beyond the limit has what is at or above it
    over = F.broadcast(want).join(sums, F.col("n_tokens") > F.col("context"), "left").groupBy("context").agg(F.min_by(F.struct("docs_from", "tokens_from"), "n_tokens").alias("x"))
    docs = F.coalesce(F.col("x.docs_from"), F.lit(0))
    return over.crossJoin(F.broadcast(total)).select("context", docs.alias("docs_over"), F.coalesce("tokens_total", F.lit(0)).alias("tokens_total"), (F.coalesce("tokens_total", F.lit(0)) - F.coalesce(F.col("x.tokens_from"), F.lit(0)) + F.col("context") * docs).alias("tokens_kept"))


def quantile(sums: DataFrame, q: float) -> DataFrame:
    """The smallest length that at least a share ``q`` of the documents do not exceed."""
    n = sums.agg(F.max("docs_from").alias("all_docs"))
    up_to = F.col("all_docs") - F.col("docs_from") + F.col("n_docs")
    return sums.crossJoin(F.broadcast(n)).where(up_to >= F.ceil(F.lit(q) * F.col("all_docs"))).agg(F.min("n_tokens").alias("n_tokens"))
