"""Language identification from character n-grams, and confidence cuts per language.

``NgramBayes`` counts n-grams once (combined before the shuffle) and keeps log
probabilities as a table. Prediction joins each document's distinct n-grams with it;
the table is broadcast while it is small, else the join shuffles. ``predict_arrow``
does the same inside Arrow batches for large inputs. A document's score per label is
the mean log probability of its n-grams, and its confidence the softmax of those.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.functions import scripts
from mlcurate.session import prepare, settle

_BROADCAST_GRAMS = 2_000_000
#: Labels of what is no language; ``noise_rows`` makes training rows for them.
NOISE = ("zxx_mojibake", "zxx_symbols")


def padded(text: Column) -> Column:
    """Lower-cased text with single spaces, also around it."""
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"\s+", " ")), F.lit(" "))


def grams(text: Column, n: int = 3) -> Column:
    return F.regexp_extract_all(padded(text), F.lit(rf"(?s)(?=(.{{{n}}}))"), F.lit(1))


def noise_rows(docs: DataFrame) -> DataFrame:
    """(text, lang): rows of common kinds of noise made from real texts: bytes read in the wrong encoding, runs of symbols."""
    wrong = docs.select(F.decode(F.encode("text", "UTF-8"), "ISO-8859-1").alias("text"), F.lit(NOISE[0]).alias("lang")).where("text rlike '[ÂÃ]'")
    symbols = docs.select(F.regexp_replace("text", r"[\p{L}\p{N}]+", "#*").alias("text"), F.lit(NOISE[1]).alias("lang"))
    return wrong.unionByName(symbols)


@dataclass
class NgramBayes:
    """Naive Bayes over n-grams; ``und_<script>`` for scripts that no label is written in (with ``script_prior``)."""

    n: int = 3
    add: float = 0.5
    tau: float = 0.5
    script_prior: bool = False
    table: DataFrame | None = None
    scripts_known: tuple[str, ...] = ()

    def fit(self, docs: DataFrame, label: str = "lang") -> NgramBayes:
        """docs: text and label. The table has a row per n-gram: a map of log probabilities by label, and the default of each label for unknown ones."""
        c = docs.select(F.col(label).alias("label"), F.explode(grams(F.col("text"), self.n)).alias("g")).groupBy("label", "g").agg(F.count(F.lit(1)).alias("c"))
        c = settle(c, "grams")
        size = c.select("g").distinct().count()
        totals = {r.label: r.t for r in c.groupBy("label").agg(F.sum("c").alias("t")).collect()}  # one row per label
        self.labels = sorted(totals)
        self.totals = totals
        logs = F.array(*[F.log((F.coalesce(F.element_at("m", x), F.lit(0)) + self.add) / (totals[x] + self.add * size)) for x in self.labels])
        self.table = c.groupBy("g").agg(F.map_from_entries(F.collect_list(F.struct("label", "c"))).alias("m")).select("g", logs.alias("logs"))
        self.size = size
        self.default = [math.log(self.add / (totals[x] + self.add * size)) for x in self.labels]
        if self.script_prior:
            self.scripts_known = tuple(r[0] for r in docs.where(~F.col(label).isin(list(NOISE))).select(scripts.dominant(F.col("text"))).distinct().collect())
        return self

    def largest(self, share: float) -> list[str]:
        """The labels with most training text, a share of all: what a classifier of a smaller family knows."""
        n = max(1, math.ceil(len(self.labels) * share - 1e-9))
        return sorted(self.labels, key=lambda x: (-self.totals[x], x))[:n]

    def predict(self, docs: DataFrame, key: str = "doc_id", labels: list[str] | None = None) -> DataFrame:
        """(key, label, conf, margin); ``labels`` restricts the choice, as a smaller model would."""
        own = [i for i, x in enumerate(self.labels) if labels is None or x in labels]
        table = F.broadcast(self.table) if self.size <= _BROADCAST_GRAMS else self.table
        g = docs.select(key, F.explode(grams(F.col("text"), self.n)).alias("g")).groupBy(key, "g").agg(F.count(F.lit(1)).alias("k"))
        logs = [F.coalesce(F.get(F.col("logs"), i), F.lit(self.default[i])) for i in own]
        s = g.join(table, "g", "left").groupBy(key).agg(*[(F.sum(F.col("k") * x) / F.sum("k")).alias(f"s{i}") for i, x in zip(own, logs, strict=True)])
        return self._decide(docs, s, [F.col(f"s{i}") for i in own], [self.labels[i] for i in own], key)

    def _decide(self, docs, s, scores, names, key) -> DataFrame:
        top = F.greatest(*scores) if len(scores) > 1 else scores[0]
        e = [F.exp(self.tau * (x - top)) for x in scores]
        total = sum(e[1:], e[0])
        ranked = F.reverse(F.array_sort(F.array(*[F.struct((x / total).alias("p"), F.lit(n).alias("label")) for x, n in zip(e, names, strict=True)])))
        got = s.select(key, ranked.alias("r")).select(key, F.col("r")[0]["label"].alias("label"), F.col("r")[0]["p"].alias("conf"), (F.col("r")[0]["p"] - F.coalesce(F.get("r", 1)["p"], F.lit(0.0))).alias("margin"))
        out = docs.select(key, "text").join(got, key, "left")
        label, conf = F.coalesce("label", F.lit("und")), F.coalesce("conf", F.lit(0.0))
        if self.script_prior:
            own = scripts.dominant(F.col("text"))
            alien = ~own.isin(list(self.scripts_known)) & (own != "Zyyy")
            label, conf = F.when(alien, F.concat(F.lit("und_"), own)).otherwise(label), F.when(alien, 1.0).otherwise(conf)
        return out.select(key, label.alias("label"), conf.alias("conf"), F.coalesce("margin", F.lit(0.0)).alias("margin"))

    def predict_arrow(self, docs: DataFrame, key: str = "doc_id") -> DataFrame:
        """The same without any shuffle: the table goes to the workers; only while it is small."""
        if self.size > _BROADCAST_GRAMS:
            return self.predict(docs, key)
        spark = prepare(docs.sparkSession)
        import numpy as np

        rows = self.table.collect()
        model = spark.sparkContext.broadcast(({r.g: i for i, r in enumerate(rows)}, np.array([*(r.logs for r in rows), self.default])))
        names, tau, n = self.labels, self.tau, self.n

        def run(batches):
            import pyarrow as pa

            index, logs = model.value
            for b in batches:
                out = []
                for t in b.column(1).to_pylist():
                    at = [index.get(t[i : i + n], -1) for i in range(len(t) - n + 1)]
                    if not at:
                        out.append(("und", 0.0, 0.0))
                        continue
                    s = logs[at].mean(0)
                    p = np.exp(tau * (s - s.max()))
                    p /= p.sum()
                    k = max(range(len(p)), key=lambda i: (p[i], names[i]))
                    out.append((names[k], float(p[k]), float(p[k] - max([0.0, *(p[i] for i in range(len(p)) if i != k)]))))
                yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c) for c in zip(*out, strict=True)]], [key, "label", "conf", "margin"])

        return docs.select(F.col(key).cast("long"), padded(F.col("text")).alias("t")).mapInArrow(run, f"{key} long, label string, conf double, margin double")


class HashedSoftmax:
    """Baseline: a linear softmax classifier over hashed n-grams, blind to scripts."""

    def __init__(self, bits: int = 12, n: int = 3, rounds: int = 20):
        self.bits, self.n, self.rounds = bits, n, rounds

    def _vectors(self, docs: DataFrame) -> DataFrame:
        from pyspark.ml.feature import HashingTF, Normalizer

        x = docs.withColumn("__g", grams(F.col("text"), self.n))
        x = HashingTF(numFeatures=1 << self.bits, inputCol="__g", outputCol="__f").transform(x)
        return Normalizer(inputCol="__f", outputCol="features").transform(x)

    def fit(self, docs: DataFrame, label: str = "lang") -> HashedSoftmax:
        from pyspark.ml.classification import LogisticRegression

        self.labels = sorted(r[0] for r in docs.select(label).distinct().collect())
        y = F.array_position(F.array(*map(F.lit, self.labels)), F.col(label)) - 1
        self.model = LogisticRegression(maxIter=self.rounds, regParam=1e-4).fit(self._vectors(docs.withColumn("label", y.cast("double"))))
        return self

    def predict(self, docs: DataFrame, key: str = "doc_id") -> DataFrame:
        from pyspark.ml.functions import vector_to_array

        p = self.model.transform(self._vectors(docs.select(key, "text"))).select(key, vector_to_array("probability").alias("p"))
        return p.select(key, F.array(*map(F.lit, self.labels))[F.array_position("p", F.array_max("p")).cast("int") - 1].alias("label"), F.array_max("p").alias("conf"))


def split_english(docs: DataFrame, pred: DataFrame, cut: float = 0.65, english: str = "en", key: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """Documents taken for English with confidence, and the rest."""
    sure = pred.where((F.col("label") == english) & (F.col("conf") >= cut)).select(key)
    return docs.join(sure, key, "left_semi"), docs.join(sure, key, "left_anti")


def adaptive_cut(pred: DataFrame, lo: float = 0.3, hi: float = 0.9, center: str = "median", std: str = "pop", accuracy: int | None = None) -> DataFrame:
    """(label, center, std, cut): one standard deviation below the centre of a language's confidences, kept within bounds."""
    mid = F.avg("conf") if center == "mean" else (F.percentile_approx("conf", 0.5, accuracy) if accuracy else F.percentile("conf", 0.5))
    s = F.stddev_pop("conf") if std == "pop" else F.coalesce(F.stddev_samp("conf"), F.lit(0.0))
    return pred.groupBy("label").agg(mid.alias("center"), s.alias("std")).select("label", F.round("center", 6).alias("center"), F.round("std", 6).alias("std"), F.round(F.least(F.lit(hi), F.greatest(F.lit(lo), F.col("center") - F.col("std"))), 6).alias("cut"))


def fixed_cut(pred: DataFrame, t: float) -> DataFrame:
    """Baseline: one cut for every language."""
    return pred.select("label").distinct().withColumn("cut", F.lit(t))


def apply_cut(pred: DataFrame, cuts: DataFrame) -> DataFrame:
    """Predictions at or above their language's cut."""
    return pred.join(F.broadcast(cuts.select("label", "cut")), "label").where(F.round("conf", 6) >= F.col("cut")).drop("cut")


def _steps(pred: DataFrame, step: float, extra: tuple[float, ...]) -> DataFrame:
    ps = [round(step * i, 6) for i in range(int(round(1 / step)))]
    at = pred.groupBy("label").agg(F.percentile("conf", ps).alias("q"))
    return at.select("label", F.explode(F.concat("q", F.array(*map(F.lit, extra)))).alias("t")).select("label", F.round("t", 6).alias("threshold")).distinct()


def sweep(pred: DataFrame, step: float = 0.05, extra: tuple[float, ...] = (0.7, 0.8, 0.9)) -> DataFrame:
    """(label, threshold, removed): cuts that remove one step more each, and values of interest, with what they remove."""
    cuts = _steps(pred, step, extra)
    x = pred.select("label", F.round("conf", 6).alias("c")).join(F.broadcast(cuts), "label")
    return x.groupBy("label", "threshold").agg(F.round(F.avg((F.col("c") < F.col("threshold")).cast("double")), 6).alias("removed"))


def best_ranges(pred: DataFrame, gold: DataFrame, key: str = "doc_id", step: float = 0.05, extra: tuple[float, ...] = (0.7, 0.8, 0.9)) -> DataFrame:
    """(label, lo, hi): least and greatest of the cuts of a sweep that give a label's best F1 against the gold labels."""
    n = gold.groupBy(F.col("lang").alias("label")).agg(F.count(F.lit(1)).alias("n_gold"))
    x = pred.join(gold.select(key, "lang"), key).select("label", F.round("conf", 6).alias("c"), (F.col("lang") == F.col("label")).alias("right"))
    x = x.join(F.broadcast(_steps(pred, step, extra)), "label").where("c >= threshold")
    x = x.groupBy("label", "threshold").agg(F.count(F.lit(1)).alias("n_kept"), F.count_if("right").alias("tp")).join(F.broadcast(n), "label")
    x = x.select("label", "threshold", F.round(2 * F.col("tp") / (F.col("n_kept") + F.col("n_gold")), 6).alias("f1"))
    best = x.groupBy("label").agg(F.max("f1").alias("b"), F.collect_list(F.struct("f1", "threshold")).alias("all"))  # a few rows per label
    ts = F.transform(F.filter("all", lambda r: r["f1"] == F.col("b")), lambda r: r["threshold"])
    return best.select("label", F.array_min(ts).alias("lo"), F.array_max(ts).alias("hi"))


def in_range(ranges: DataFrame, tolerance: float = 0.005) -> DataFrame:
    """``ranges`` (label, lo, hi or null, formula) with whether the formula lies in the best range."""
    return ranges.withColumn("inside", F.col("formula").between(F.col("lo") - tolerance, F.coalesce("hi", F.lit(1.0)) + tolerance))


def cousin_matrix(pred: DataFrame, gold: DataFrame, key: str = "doc_id") -> DataFrame:
    """(lang, label, n, share): where each language's documents go."""
    x = pred.join(gold.select(key, "lang"), key).groupBy("lang", "label").agg(F.count(F.lit(1)).alias("n"))
    from pyspark.sql import Window

    return x.select("lang", "label", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("lang")), 6).alias("share"))


def quality(pred: DataFrame, gold: DataFrame, key: str = "doc_id") -> DataFrame:
    """(lang, precision, recall, f1) of labels."""
    x = pred.join(gold.select(key, "lang"), key)
    tp = x.where("lang = label").groupBy("lang").agg(F.count(F.lit(1)).alias("tp"))
    n = x.groupBy("lang").agg(F.count(F.lit(1)).alias("n_gold"))
    m = x.groupBy(F.col("label").alias("lang")).agg(F.count(F.lit(1)).alias("n_pred"))
    z = n.join(tp, "lang", "left").join(m, "lang", "left").fillna(0)
    p, r = F.coalesce(F.col("tp") / F.nullif("n_pred", F.lit(0)), F.lit(0.0)), F.col("tp") / F.col("n_gold")
    return z.select("lang", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0), 6).alias("f1"))
