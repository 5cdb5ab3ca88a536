"""Near-duplicate clusters by banded MinHash over word 5-grams, per language or any wider key.

Identical texts collapse first, with their count. A document's signature is made where
its text is read, without a shuffle; bands, star edges and components follow, and one
document per cluster stays with the cluster's size.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructType

from mlcurate.dedup.components import connected
from mlcurate.functions import words as W
from mlcurate.session import discard, prepare, release, settle

PRIME = (1 << 31) - 1
#: Shingles whose values are computed at once.
SLICE = 4096
#: Parts of the shingles whose pairs are counted one after the other.
PASSES = 8
#: Shingles that two sets must share in their beginnings: one or two are shared by chance, as hashes of 28 bits meet.
SHARED = 3
#: Slots that the sets with a shingle are counted in; rows that are sent to every executor; shingles that pairs carry through shuffles at once.
SLOTS, BROADCAST_ROWS, AT_ONCE = 1 << 18, 500_000, 40_000_000


@dataclass(frozen=True)
class Config:
    """14 bands of 8 over 5-grams; ``family``: 'xx' (fast, 64 bits) or 'affine31' (any SQL engine can repeat it)."""

    bands: int = 14
    rows: int = 8
    gram: int = 5
    family: str = "affine31"

    @property
    def coefficients(self) -> list[tuple[int, int]]:
        """Fixed pairs (a, b) of the affine family, by a linear congruence."""
        out, x = [], 20_240_613
        for _ in range(self.bands * self.rows):
            x = (x * 48_271) % PRIME
            a = x
            x = (x * 48_271) % PRIME
            out.append((max(a, 1), x))
        return out


def _grams(docs: DataFrame, cfg: Config) -> Column:
    """Distinct word n-grams, words by the tokenizer of the row's language."""
    return W.let(W.words_in(F.col("text"), W.language_of(docs)), lambda w: F.array_distinct(W.ngrams(w, cfg.gram)))


def _hash(s: Column, cfg: Config) -> Column:
    return F.xxhash64(s) if cfg.family == "xx" else F.conv(F.substring(F.md5(s), 1, 7), 16, 10).cast("long")


def shingles(docs: DataFrame, cfg: Config = Config(), keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """(keep, g): hashes of distinct word n-grams; shorter texts are one, texts without words have none."""
    x = docs.select(*keep, F.explode(_grams(docs, cfg)).alias("s"))
    return x.select(*keep, _hash(F.col("s"), cfg).alias("g"))


def minima(g: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least value of every affine function over hashes below 2**28; a slice of long texts at a time, so memory stays bounded."""
    low = np.full(len(a), PRIME, np.int64)
    for i in range(0, len(g), SLICE):
        np.minimum(low, ((g[i : i + SLICE, None] * a + b) % PRIME).min(0), out=low)
    return low


def signatures(docs: DataFrame, cfg: Config = Config(), keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """(keep, sig): minima of every hash function, a row per document that has words, without a shuffle."""
    n = cfg.bands * cfg.rows
    x = docs.select(*keep, _grams(docs, cfg).alias("__s")).where(F.size("__s") > 0)
    x = x.select(*keep, F.transform("__s", lambda s: _hash(s, cfg)).alias("__g"))
    if cfg.family == "xx":
        each = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.array_min(F.transform("__g", lambda g: F.xxhash64(i, g))))
        return x.select(*keep, each.alias("sig"))
    prepare(docs.sparkSession)
    a, b = (np.array(c, np.int64) for c in zip(*cfg.coefficients, strict=True))

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            lists = batch.column(batch.num_columns - 1)
            ends, values = lists.offsets.to_numpy(), lists.values.to_numpy()
            sig = [minima(values[s:e], a, b) for s, e in zip(ends, ends[1:], strict=False)]
            flat = np.concatenate(sig) if sig else np.empty(0, np.int64)
            made = pa.ListArray.from_arrays(pa.array(np.arange(len(sig) + 1, dtype=np.int32) * n), pa.array(flat))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], made], [*batch.schema.names[:-1], "sig"])

    schema = StructType(list(x.schema.fields)[:-1]).add("sig", ArrayType(LongType()))
    return x.mapInArrow(run, schema)


def band_keys(sigs: DataFrame, cfg: Config = Config(), keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """(keep, band, bkey)."""
    part = lambda b: F.slice("sig", b * cfg.rows + 1, cfg.rows)
    key = lambda b: F.xxhash64(part(b)).cast("string") if cfg.family == "xx" else F.md5(F.array_join(part(b).cast("array<string>"), ","))
    return sigs.select(*keep, F.posexplode(F.array(*[key(b) for b in range(cfg.bands)])).alias("band", "bkey"))


def star_edges(bands: DataFrame, scope: tuple[str, ...] = ("lang",)) -> DataFrame:
    """(src, dst): every member of a bucket and its smallest id; linear in the rows.

    Smallest ids combine before the shuffle and buckets of one document fall away; the join with the rest can be split
    where a bucket is large, which a window over buckets can't be."""
    key = [*scope, "band", "bkey"]
    least = bands.groupBy(*key).agg(F.min("doc_id").alias("dst"), F.max("doc_id").alias("__most")).where("dst < __most").drop("__most")
    return bands.join(least, key).select(F.col("doc_id").alias("src"), "dst").where("src != dst").distinct()


def exact(docs: DataFrame, scope: tuple[str, ...] = ("lang",)) -> DataFrame:
    """(scope, doc_id, n): one row per distinct text, the smallest id, with how many texts it stands for."""
    return docs.groupBy(*scope, F.sha2(F.coalesce("text", F.lit("")), 256).alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")).drop("h")


def clusters(docs: DataFrame, cfg: Config = Config(), scope: tuple[str, ...] = ("lang",), algo: str = "star") -> DataFrame:
    """(doc_id, scope, comp, cluster_size, keep) of every document."""
    h = F.sha2(F.coalesce("text", F.lit("")), 256)
    narrow = docs.select("doc_id", *scope, h.alias("h"))
    reps = settle(narrow.groupBy(*scope, "h").agg(F.min("doc_id").alias("rep")), "reps")
    texts = docs.join(reps.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")
    bands = settle(band_keys(signatures(texts, cfg, ("doc_id", *scope)), cfg, ("doc_id", *scope)), "bands")
    comp = connected(star_edges(bands, scope), algo)
    named = narrow.join(reps, [*scope, "h"]).join(comp.withColumnRenamed("id", "rep"), "rep", "left").select("doc_id", *scope, F.coalesce("comp", "rep").alias("comp"))
    named = settle(named, "clusters")
    sizes = named.groupBy("comp").agg(F.count(F.lit(1)).alias("cluster_size"))
    return named.join(sizes, "comp").select("doc_id", *scope, "comp", "cluster_size", (F.col("doc_id") == F.col("comp")).alias("keep"))


def keep_one(docs: DataFrame, found: DataFrame, by: str = "min_id") -> DataFrame:
    """``docs`` reduced to one per cluster, with ``cluster_size``; by 'min_id' or 'longest'."""
    if by == "min_id":
        best = found.where("keep").select("doc_id", "cluster_size")
    else:
        lens = docs.select("doc_id", F.length("text").alias("n")).join(found, "doc_id")
        best = lens.groupBy("comp").agg(F.max_by("doc_id", F.struct("n", -F.col("doc_id"))).alias("doc_id"), F.first("cluster_size").alias("cluster_size")).drop("comp")
    return docs.join(best, "doc_id")


def drop_large(docs: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """Baseline: clusters of ``k`` or more go, the rest stays whole."""
    return docs.join(found.where(F.col("cluster_size") < k).select("doc_id", "cluster_size"), "doc_id")


def curve(s: float, cfg: Config = Config()) -> float:
    """Chance that a pair of similarity ``s`` shares a bucket."""
    return 1 - (1 - s**cfg.rows) ** cfg.bands


def _in_common(least: float) -> Column:
    """How many shingles sets of na and nb share at least, if their similarity reaches ``least``."""
    return (F.col("na") + F.col("nb")) * (least / (1 + least)) - 1e-6


def _begins(sets: DataFrame, least: float, scope: tuple[str, ...]) -> DataFrame:
    """(doc_id, scope, n, p): how many shingles a set has, and its first ones in an order of about how many sets hold them, rare ones first."""
    counts = sets.select(F.explode("g").alias("v")).groupBy(F.pmod(F.xxhash64("v"), F.lit(SLOTS)).alias("slot")).agg(F.count(F.lit(1)).alias("c")).collect()
    class_of = bytearray(SLOTS)
    for slot, c in counts:
        class_of[slot] = min(int(6 * math.log2(c)), 127)
    held = F.lit(class_of)
    kind = lambda v: F.ascii(F.substring(held, F.pmod(F.xxhash64(v), F.lit(SLOTS)).cast("int") + 1, F.lit(1)).cast("string"))
    n = F.size("g")
    length = F.greatest(n - F.greatest(F.ceil(n * least - 1e-6), F.lit(1)) + SHARED, F.lit(0)).cast("int")
    ordered = F.array_sort(F.transform("g", lambda v: F.struct(kind(v).alias("kind"), v.alias("v"))))
    return sets.select("doc_id", *scope, n.alias("n"), F.transform(F.slice(ordered, F.lit(1), length), lambda s: s["v"]).alias("p"))


def _alike(pairs: DataFrame, sets: DataFrame, least: float, scope: tuple[str, ...]) -> DataFrame:
    """(a, b, scope, sim), settled: the pairs whose whole sets reach ``least``. Parts of the pairs carry about ``AT_ONCE`` shingles through shuffles."""
    total = pairs.agg(F.sum((F.col("na") + F.col("nb")).cast("long"))).first()[0] or 0
    parts, out = max(-(-total // AT_ONCE), 1), []
    for i in range(parts):
        release(pairs.sparkSession)
        part = pairs.where(F.pmod(F.xxhash64("a", "b"), F.lit(parts)) == i)
        ends = settle(part.select(F.col("a").alias("doc_id"), *scope).union(part.select(F.col("b").alias("doc_id"), *scope)).distinct(), "ends")
        near = sets.join(F.broadcast(ends) if ends.count() <= BROADCAST_ROWS else ends, ["doc_id", *scope], "left_semi")
        side = lambda c: near.select(F.col("doc_id").alias(c), *scope, F.col("g").alias(f"g{c}"))  # noqa: B023, E731
        both = part.join(side("a"), ["a", *scope]).join(side("b"), ["b", *scope]).select("a", "b", *scope, "na", "nb", F.size(F.array_intersect("ga", "gb")).alias("k"))
        out.append(settle(both.select("a", "b", *scope, (F.col("k") / (F.col("na") + F.col("nb") - F.col("k"))).alias("sim")).where(F.col("sim") >= least), "alike"))
        discard(ends)
    return reduce(DataFrame.union, out)


def exact_pairs(docs: DataFrame, least: float, cfg: Config = Config(), scope: tuple[str, ...] = ("lang",)) -> DataFrame:
    """(a, b, sim) of all pairs with similarity at least ``least``; for measuring accuracy.

    Documents with the same set of shingles are one class, so copies are paired by membership and never by shingle. Sets are put in one
    order, rare shingles first. A set of n shares at least ``least * n`` with a partner, so the first ``SHARED`` that two partners share stand
    among the first ``n - least * n + SHARED`` of both; only these beginnings are joined, in ``PASSES`` parts of the shingles, one after the other, whose
    shuffles go in between. Pairs that share so many are compared by their whole sets, some at a time. Rows under one doc_id and scope count as one document."""
    spark, keys = docs.sparkSession, list(scope)
    kind = "array<int>" if cfg.family == "affine31" else "array<long>"  # the hashes of affine31 have 28 bits
    x = docs.dropna(subset=keys).select("doc_id", *scope, F.transform(_grams(docs, cfg), lambda s: _hash(s, cfg)).cast(kind).alias("g")).where(F.size("g") > 0)
    x = settle(x.select("doc_id", *scope, F.array_sort(F.array_distinct("g")).alias("g")), "sets")
    if x.count() > x.select("doc_id", *scope).distinct().count():
        x = settle(x.groupBy("doc_id", *scope).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("g")))).alias("g")), "sets")
    named = settle(x.select("doc_id", *scope, F.sha2(F.array_join(F.col("g").cast("array<string>"), ","), 256).alias("h"), F.size("g").alias("n")), "named")
    least_id = named.groupBy(*scope, "h").agg(F.min("doc_id").alias("rep"))
    members = settle(named.join(least_id, [*scope, "h"]).select("doc_id", *scope, "rep", "n"), "members")
    discard(named)
    copies = members.where("doc_id != rep").select("doc_id", *scope)
    own = x.join(F.broadcast(copies) if copies.count() <= BROADCAST_ROWS else copies, ["doc_id", *scope], "left_anti")
    begins = settle(_begins(own, least, scope), "begins")
    found = []
    for i in range(PASSES):
        release(spark)
        part = F.filter(F.transform("p", lambda v, at: F.struct(v.alias("g"), at.alias("at"))), lambda s: F.pmod(s["g"], F.lit(PASSES)) == i)
        g = begins.select("doc_id", *scope, "n", F.explode(part).alias("s")).select("doc_id", *scope, "n", "s.g", "s.at")
        shared = settle(g.join(g.groupBy(*scope, "g").agg(F.count(F.lit(1)).alias("c")).where("c > 1").drop("c"), [*scope, "g"]), "shared")
        side = lambda c: shared.select(*scope, "g", F.col("doc_id").alias(c), F.col("n").alias(f"n{c}"), (F.col("n") - F.col("at")).alias(f"left_{c}"))  # noqa: B023, E731
        pair = side("a").join(side("b"), [*scope, "g"]).where("a < b").where(F.least("na", "nb") >= least * F.greatest("na", "nb") - 1e-6)
        pair = pair.where(F.least("left_a", "left_b") + (SHARED - 1) >= _in_common(least))
        found.append(settle(pair.groupBy("a", "b", "na", "nb", *scope).agg(F.count(F.lit(1)).alias("k")), "common"))
        discard(shared)
    release(spark)
    some = reduce(DataFrame.union, found).groupBy("a", "b", "na", "nb", *scope).agg(F.sum("k").alias("k"))
    some = settle(some.where(F.col("k") >= F.least(F.lit(float(SHARED)), _in_common(least))).drop("k"), "candidates")
    discard(begins, *found)
    pair = _alike(some, x, least, scope)
    discard(x, some)
    release(spark)
    side = lambda c: members.select(F.col("rep").alias(c), *scope, F.col("doc_id").alias(f"m{c}"))
    across = pair.join(side("a"), ["a", *scope]).join(side("b"), ["b", *scope]).select(F.least("ma", "mb").alias("a"), F.greatest("ma", "mb").alias("b"), "sim")
    within = side("a").join(side("a").withColumnRenamed("ma", "mb"), ["a", *scope]).where("ma < mb").select(F.col("ma").alias("a"), F.col("mb").alias("b"), F.lit(1.0).alias("sim"))
    return across.where("a < b").union(within.where(F.lit(least <= 1)))


def recall(pairs: DataFrame, edges_or_bands: DataFrame) -> DataFrame:
    """(bin, n, found): pairs by tenths of similarity, and how many share a bucket; bands: doc_id, band, bkey."""
    held = edges_or_bands.groupBy("doc_id").agg(F.collect_set(F.xxhash64("band", "bkey")).alias("k"))
    side = lambda c: held.select(F.col("doc_id").alias(c), F.col("k").alias(f"k{c}"))
    x = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    x = x.select((F.floor(F.round(F.col("sim"), 9) * 10) / 10).alias("bin"), F.coalesce(F.arrays_overlap("ka", "kb"), F.lit(False)).cast("int").alias("hit"))
    return x.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.sum("hit").alias("found"))
