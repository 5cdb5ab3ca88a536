"""N-gram Jaccard join with Bayesian candidate pruning.

Texts are sets of five-word shingles (lower-cased words; a text of one to four words
is one shingle). Identical texts form a class and go on as one row. Each class gets
``HASHES`` MinHash values; bands of ``ROWS`` values put classes into buckets. A
candidate's values are compared ``STEP`` at a time: the number that agree gives a
Beta posterior of the similarity (uniform prior), and the pair is dropped as soon as
the probability that it reaches the threshold falls below ``TOLERANCE``. What is
left is verified exactly, shingle by shingle.

No list of all pairs of a group is written. Bucket members are compared with the
bucket's pivot; pairs that survive pruning make families. Texts within half of the
allowed distance of a pivot form a core: Jaccard distance is a metric, so all of a
core's texts are linked with each other, and a family that is one core needs no more
work. The other pairs of a family are pruned and verified inside tasks that each see
two bounded blocks of it and give back one row per text: how many links, and the
smallest text reached. Members of one bucket and different families are pruned the
same way, and the few pairs left are verified one by one.

Result per document: doc_id, class_id (smallest doc_id with the same text), n_copies,
n_links (other documents whose text is identical or similar enough), group_id
(smallest doc_id reached over links).

Defined cases: null and empty texts, and texts without words, have no shingles, no
links and a group of their own; documents with a null doc_id come back with nulls;
rows that repeat a doc_id count as one document per distinct text; extra columns are ignored.
Texts are told apart by hashes of their own, so texts under one doc_id don't mix.
"""

from __future__ import annotations

import math
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.dedup.components import connected
from mlcurate.llm import buckets
from mlcurate.session import discard, prepare, settle

GRAM, THRESHOLD = 5, 0.8
#: 24 bands of 4: a pair at 0.8 meets in a bucket but for 3 in a million.
HASHES, ROWS, STEP, TOLERANCE = 96, 4, 16, 1e-6
#: What one block of a family may hold; a task sees two blocks.
BLOCK_TEXTS, BLOCK_CHARS = 200, 1_000_000
_WORD = re.compile(r"\w+")
_MULT = (np.random.default_rng(20240611).integers(1, 1 << 62, HASHES, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_ADD = np.random.default_rng(1311).integers(0, 1 << 63, HASHES, dtype=np.uint64)
_P1, _P2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def shingles(text: str | None, gram: int = GRAM) -> set:
    """The set that similarity is measured on."""
    w = _WORD.findall((text or "").lower())
    return set(zip(*(w[i:] for i in range(gram)), strict=False)) if len(w) >= gram else {tuple(w)} if w else set()


class _Hasher:
    """64-bit hashes of the shingles of a text, by way of a table of word hashes."""

    def __init__(self, gram: int):
        self.gram, self.known = gram, {}

    def __call__(self, text: str | None) -> np.ndarray:
        import xxhash

        w = _WORD.findall((text or "").lower())
        known = self.known
        if len(known) > 400_000:
            known.clear()
        for x in set(w).difference(known):
            known[x] = xxhash.xxh64_intdigest(x)
        h = np.fromiter(map(known.__getitem__, w), np.uint64, len(w))
        n, g = len(h), self.gram
        if not n:
            return h
        k = min(n, g)
        out = np.zeros(n - k + 1, np.uint64)
        for i in range(k):
            out = (out ^ h[i : n - k + 1 + i]) * _P1
            out ^= out >> np.uint64(29)
        return out * _P2


def signature(hashes: np.ndarray) -> np.ndarray:
    """Minima of ``HASHES`` functions, 32 bits each."""
    least = np.full(HASHES, np.iinfo(np.uint32).max, np.uint32)
    for i in range(0, len(hashes), 512):
        x = hashes[i : i + 512, None] * _MULT + _ADD
        np.minimum(least, (x >> np.uint64(32)).astype(np.uint32).min(0), out=least)
    return least


def least_agreeing(threshold: float, tolerance: float = TOLERANCE) -> list[tuple[int, int]]:
    """(k, m): after k values, a pair with fewer than m that agree is dropped."""
    s = np.linspace(0, 1, 20_001)[1:-1]
    out = []
    for k in range(STEP, HASHES + 1, STEP):
        m = 0
        while m <= k:
            logs = m * np.log(s) + (k - m) * np.log1p(-s)
            p = np.exp(logs - logs.max())
            if p[s >= threshold].sum() / p.sum() >= tolerance:
                break
            m += 1
        out.append((k, m))
    return out


def surviving(a: np.ndarray, b: np.ndarray, limits: list[tuple[int, int]]) -> np.ndarray:
    """Which pairs of signature rows pass every comparison step; dropped pairs are not compared further."""
    alive, same, begin = np.arange(len(a)), np.zeros(len(a), np.int64), 0
    for k, m in limits:
        same[alive] += (a[alive, begin:k] == b[alive, begin:k]).sum(1)
        alive = alive[same[alive] >= m]
        begin = k
    return alive


def _text_key(text):
    """Columns that tell texts apart: two hashes and a length."""
    t = F.coalesce(text, F.lit(""))
    return [F.xxhash64(t).alias("h1"), F.hash(t, F.length(t)).alias("h2"), F.length(t).alias("h3")]


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("__text"), *_text_key(F.col("text")))


def classes(docs: DataFrame, gram: int) -> DataFrame:
    """(h1, h2, h3, id, doc, n, sig) per distinct text: a number of its own, smallest doc_id, rows, signature (null without shingles)."""
    from mlcurate.llm.tokens import let_go

    def run(batches):
        import pyarrow as pa

        let_go()
        hasher = _Hasher(gram)
        for b in batches:
            sigs = []
            for t in b.column(1).to_pylist():
                h = hasher(t)
                sigs.append(signature(h).view(np.int32) if len(h) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), *b.columns[2:], pa.array(sigs, pa.list_(pa.int32()))], ["doc_id", "h1", "h2", "h3", "sig"])

    signed = _keyed(docs).where("doc_id is not null").mapInArrow(run, "doc_id long, h1 long, h2 int, h3 int, sig array<int>")
    x = signed.groupBy("h1", "h2", "h3").agg(F.min(F.struct("doc_id", "sig")).alias("x"), F.count(F.lit(1)).alias("n"))
    return x.select("h1", "h2", "h3", F.monotonically_increasing_id().alias("id"), F.col("x.doc_id").alias("doc"), "n", F.col("x.sig").alias("sig"))


def _pruned(pairs: DataFrame, sigs: DataFrame, threshold: float) -> DataFrame:
    """(a, b): pairs that survive the comparison of their signatures."""
    limits = least_agreeing(threshold)
    both = pairs.join(sigs.select(F.col("id").alias("a"), F.col("sig").alias("sa")), "a").join(sigs.select(F.col("id").alias("b"), F.col("sig").alias("sb")), "b")

    def prune(batches):
        import pyarrow as pa

        for b in batches:
            sa, sb = (np.asarray(b.column(i).flatten()).reshape(-1, HASHES) for i in (2, 3))
            yield pa.RecordBatch.from_arrays([c.take(pa.array(surviving(sa, sb, limits))) for c in b.columns[:2]], ["a", "b"])

    return both.select("a", "b", "sa", "sb").mapInArrow(prune, "a long, b long")


def _verified(pairs: DataFrame, texts: DataFrame, gram: int, least: float) -> DataFrame:
    """(a, b): pairs whose exact similarity is at least ``least``."""
    full = pairs.join(texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b")

    def verify(batches):
        import pyarrow as pa

        for b in batches:
            out, last, held = [], None, set()
            for x, y, s, t in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if x != last:
                    last, held = x, shingles(s, gram)
                other = shingles(t, gram)
                shared = len(held & other)
                if shared >= least * (len(held) + len(other) - shared) - 1e-12:
                    out.append((x, y))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in (0, 1)], ["a", "b"])

    return full.select("a", "b", "ta", "tb").mapInArrow(verify, "a long, b long")


def _block_pairs(table, apart: str, limits) -> tuple[np.ndarray, np.ndarray]:
    """Positions (i, j) of the pairs of two blocks (or inside one) that differ in ``apart`` and survive pruning."""
    lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
    block, group = np.asarray(table.column("block")), np.asarray(table.column(apart))
    sig = np.asarray(table.column("sig").combine_chunks().flatten()).reshape(-1, HASHES)
    right = np.flatnonzero(block == hi)
    found = []
    for i in np.flatnonzero(block == lo):
        other = right if lo != hi else right[right > i]
        other = other[group[other] != group[i]]
        if len(other):
            found += [(i, other[k]) for k in surviving(np.broadcast_to(sig[i], (len(other), HASHES)), sig[other], limits)]
    x = np.array(found, np.int64).reshape(-1, 2)
    return x[:, 0], x[:, 1]


def _within(members: DataFrame, gram: int, threshold: float) -> DataFrame:
    """(id, links, least): links of texts inside their families, by pairs of blocks; members: fam, id, core, n, sig, text."""
    limits = least_agreeing(threshold)
    dealt = blocks_of(members)

    def run(table):
        import pyarrow as pa

        ids, n = np.asarray(table.column("id")), np.asarray(table.column("n"))
        sets: dict[int, set] = {}
        links, least = np.zeros(len(ids), np.int64), np.arange(len(ids))

        def root(i):
            while least[i] != i:
                least[i] = i = least[least[i]]
            return i

        def held(i):
            if i not in sets:
                sets[i] = shingles(table.column("text")[i].as_py(), gram)
            return sets[i]

        for i, j in zip(*map(np.ndarray.tolist, _block_pairs(table, "core", limits)), strict=True):
            a, b = held(i), held(j)
            shared = len(a & b)
            if shared >= threshold * (len(a) + len(b) - shared) - 1e-12:
                links[i] += n[j]
                links[j] += n[i]
                a, b = root(i), root(j)
                least[max((ids[a], a), (ids[b], b))[1]] = min((ids[a], a), (ids[b], b))[1]
        low = ids[[root(i) for i in range(len(ids))]]
        some = np.flatnonzero(links)
        return pa.table({"id": pa.array(ids[some], pa.int64()), "links": pa.array(links[some], pa.int64()), "least": pa.array(low[some], pa.int64())})

    return dealt.groupBy("fam", "lo", "hi").applyInArrow(run, "id long, links long, least long")


def blocks_of(members: DataFrame) -> DataFrame:
    """Blocks of at most about ``BLOCK_TEXTS`` texts and ``BLOCK_CHARS`` characters."""
    weight = F.greatest(F.lit(BLOCK_CHARS // BLOCK_TEXTS), F.length("text"))
    return buckets.blocks(members, "fam", "core", weight, BLOCK_CHARS)


def _beyond(mixed: DataFrame, threshold: float) -> DataFrame:
    """(a, b): pairs of one bucket and different families that survive pruning; mixed: key, id, grp, sig."""
    limits = least_agreeing(threshold)
    dealt = buckets.blocks(mixed, "key", "grp", F.lit(1), BLOCK_TEXTS)

    def run(table):
        import pyarrow as pa

        ids = np.asarray(table.column("id"))
        i, j = _block_pairs(table, "grp", limits)
        return pa.table({"a": pa.array(np.minimum(ids[i], ids[j]), pa.int64()), "b": pa.array(np.maximum(ids[i], ids[j]), pa.int64())})

    return dealt.groupBy("key", "lo", "hi").applyInArrow(run, "a long, b long").distinct()


def _linked(docs: DataFrame, gram: int, threshold: float) -> DataFrame:
    """Per distinct text: h1, h2, h3, class_id, n_copies, n_links, group_id, and whether it leads its group."""
    prepare(docs.sparkSession)
    reps = settle(classes(docs, gram), "classes")
    signed = reps.where("sig is not null").select("id", "n", "sig")
    keys = F.array(*[F.xxhash64(F.lit(b), *[F.element_at("sig", b * ROWS + r + 1) for r in range(ROWS)]) for b in range(HASHES // ROWS)])
    m = buckets.members(signed.select("id", F.explode(keys).alias("key")))
    ids = m.select("id").distinct()
    some = settle(signed.join(ids, "id", "left_semi"), "signatures")
    kept = settle(_pruned(buckets.star(m), some, threshold), "star")
    fam = settle(connected(kept.select(F.col("a").alias("src"), F.col("b").alias("dst"))).withColumnRenamed("comp", "grp"), "families")
    beyond = settle(_beyond(buckets.mixed(m, fam).join(some.select("id", "sig"), "id"), threshold), "beyond")
    discard(m)
    wanted = fam.select("id").union(beyond.select("a")).union(beyond.select("b")).distinct()
    named = reps.select("id", "doc", "h1", "h2", "h3").join(wanted, "id", "left_semi")
    texts = _keyed(docs).withColumnsRenamed({"doc_id": "doc", "__text": "text"}).join(named, ["doc", "h1", "h2", "h3"])
    texts = settle(texts.select("id", "text").dropDuplicates(["id"]), "texts")

    near = 1 - (1 - threshold) / 2
    cores = settle(_verified(kept, texts, gram, near).groupBy(F.col("b").alias("id")).agg(F.min("a").alias("core")), "cores")
    # a core's name is a text of it, too, unless that text lies in another core
    of = fam.select("id", F.col("grp").alias("fam")).join(cores, "id", "left").select("id", "fam", F.coalesce("core", "id").alias("core")).join(some, "id")
    several = of.groupBy("fam").agg(F.min("core").alias("lo"), F.max("core").alias("hi")).where("lo != hi").select("fam")
    inside = settle(_within(of.join(several, "fam", "left_semi").join(texts, "id"), gram, threshold), "inside")
    outside = settle(_verified(beyond, texts, gram, threshold), "outside")
    discard(texts, kept, beyond)

    sizes = of.groupBy("core").agg(F.sum("n").alias("core_n"))
    in_core = of.select("id", "core").join(sizes, "core").select("id", "core_n")
    ends = outside.select(F.col("a").alias("id"), F.col("b").alias("other")).union(outside.select(F.col("b").alias("id"), F.col("a").alias("other")))
    counted = inside.select("id", "links").union(ends.join(reps.select(F.col("id").alias("other"), "n"), "other").select("id", F.col("n").alias("links"))).groupBy("id").agg(F.sum("links").alias("more"))
    edges = inside.select(F.col("id").alias("src"), F.col("least").alias("dst")).union(outside.select("a", "b")).union(cores.select("id", "core"))
    comp = connected(edges)
    # a group's first text: smallest doc_id, then by hash where texts share one
    own = F.struct("doc", "h1", "h2", "h3")
    first = comp.join(reps.select("id", own.alias("own")), "id").groupBy("comp").agg(F.min("own").alias("first"))
    led = comp.join(first, "comp").select("id", "first")
    per_class = reps.withColumn("bare", F.col("sig").isNull()).drop("sig").join(in_core, "id", "left").join(counted, "id", "left").join(led, "id", "left")
    alike = F.when(F.col("bare"), F.lit(1)).otherwise(F.coalesce("core_n", "n"))
    group = F.when(~F.col("bare"), F.coalesce("first.doc", "doc"))
    lead = F.coalesce(F.col("first") == own, F.lit(True))
    return per_class.select("h1", "h2", "h3", F.col("doc").alias("class_id"), F.col("n").alias("n_copies"), (alike - 1 + F.coalesce("more", F.lit(0))).alias("n_links"), group.alias("group_id"), lead.alias("lead"))


def near_duplicates(docs: DataFrame, gram: int = GRAM, threshold: float = THRESHOLD) -> DataFrame:
    """One row per document; see the module's text."""
    out = _keyed(docs).drop("__text").join(_linked(docs, gram, threshold), ["h1", "h2", "h3"], "left")
    has_id = F.col("doc_id").isNotNull()
    return out.select("doc_id", *[F.when(has_id, F.col(c)).alias(c) for c in ("class_id", "n_copies", "n_links")], F.when(has_id, F.coalesce("group_id", "doc_id")).alias("group_id"))


def keep_one(docs: DataFrame, gram: int = GRAM, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` with one document of each group: the text with the smallest doc_id, under that doc_id.

    A row goes only if its own text belongs to a group that another row stands for; other texts under its doc_id stay.
    Rows with a null doc_id and texts without words stay; rows that repeat the kept document in full stay with it."""
    per_class = _linked(docs, gram, threshold).where("group_id is not null")
    rows = _keyed(docs).drop("__text").where("doc_id is not null").join(per_class, ["h1", "h2", "h3"])
    lost = rows.where(~F.col("lead") | (F.col("doc_id") != F.col("class_id"))).select(F.col("doc_id").alias("__d"), *[F.col(c).alias(f"__{c}") for c in ("h1", "h2", "h3")]).distinct()
    x = docs.select(F.struct("*").alias("__row"), F.col("doc_id").cast("long").alias("__doc"), *_text_key(F.col("text")))
    same = (F.col("__doc") == F.col("__d")) & (F.col("h1") == F.col("__h1")) & (F.col("h2") == F.col("__h2")) & (F.col("h3") == F.col("__h3"))
    return x.join(lost, same, "left_anti").select("__row.*")


def links_expected(s: float) -> float:
    """Chance that a pair of similarity ``s`` meets in a bucket."""
    return 1 - math.pow(1 - s**ROWS, HASHES // ROWS)
