"""Benchmark decontamination by SimHash windows, multi-index Hamming blocks and exact verification.

Words are lower-cased runs of letters, marks and digits. For each benchmark item the
documents are searched by windows of as many words as the item has. A window can only
be similar to an item if it holds most of the item's five-word shingles, so windows
are laid where an item's shingles stand, in documents that hold enough of them to
reach the threshold; no window that does reach it lies elsewhere. A window's SimHash of
``BITS`` bits is looked up among the items' by blocks of sixteen bits: two fingerprints
within ``RADIUS`` bits differ by at most ``RADIUS // BLOCKS`` bits in one of the blocks, so
each item is entered under every value that near to its own block, and no fingerprint
within the radius is missed, while five pairs of unlike ones in six share no block. Two
texts at the threshold differ by 39 bits, with a standard error of 6, so the radius leaves
out 2 in 100,000. A fingerprint says little about few shingles: items of fewer than
``SHORT`` are tried with every window that was laid for them. What is found is verified
exactly: weighted Jaccard similarity of shingles, a shingle's weight being how often it stands.

Everything is DataFrame expressions. Result: a row per document and item that meet:
doc_id, item_id, start (word), n_words, similarity (best window).

Defined cases: null and empty texts and items without words match nothing; items of
fewer than five words are one shingle; a document shorter than an item is one window;
rows with a null doc_id match under a null doc_id; repeated rows give one match; extra
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.session import discard, settle

GRAM, THRESHOLD = 5, 0.8
#: Bits of a fingerprint, its blocks of sixteen bits, and the largest distance at which one is found.
BITS, BLOCKS, RADIUS = 256, 16, 63
#: Shingles below which an item is tried without a fingerprint.
SHORT = 16
#: Rows that a side may have to be sent to every executor; beyond it the join shuffles.
BROADCAST_ROWS = 1_000_000
_WORD = r"[\p{L}\p{M}\p{N}]+"


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(_WORD), F.lit(0))


def _let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once, also under a generator."""
    return F.get(F.transform(F.array(value), body), 0)


def _starts(w: Column, gram: int) -> Column:
    """Where shingles begin; a text of fewer words than ``gram`` is one shingle, one without words none."""
    return F.when(F.size(w) == 0, F.array().cast("array<int>")).otherwise(F.sequence(F.lit(0), F.greatest(F.size(w) - gram, F.lit(0))))


def _hashes(w: Column, gram: int) -> Column:
    return F.transform(_starts(w, gram), lambda i: F.xxhash64(*[F.coalesce(F.get(w, i + k), F.lit("")) for k in range(gram)]))


def _shingles(w: Column, gram: int) -> Column:
    return F.transform(_starts(w, gram), lambda i: F.array_join(F.slice(w, i + 1, F.lit(gram)), " "))


def _numbered(shingles: Column) -> Column:
    """Each shingle with which occurrence it is: sets of these have the multiset's similarity."""
    return F.transform(shingles, lambda x, i: F.concat(x, F.lit("#"), F.size(F.filter(F.slice(shingles, 1, i), lambda y: y == x)).cast("string")))


def simhash(features: Column) -> Column:
    """``BITS`` bits, in longs: each bit is the majority of that bit over the features' hashes; repeats are features of their own."""

    def word(k: int) -> Column:
        hashes = F.transform(features, lambda x: F.xxhash64(F.lit(k), x))
        bit = lambda every, b: F.aggregate(every, F.lit(0), lambda a, h: a + F.getbit(h, b).cast("int") * 2 - 1) > 0
        bits = lambda every: F.transform(F.sequence(F.lit(0), F.lit(63)), lambda b: F.when(bit(every, b), F.call_function("shiftleft", F.lit(1).cast("long"), b)).otherwise(F.lit(0).cast("long")))
        return _let(hashes, lambda every: F.aggregate(bits(every), F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x)))

    return F.array(*[word(k) for k in range(BITS // 64)])


def distance(p: Column, q: Column) -> Column:
    """Bits in which two fingerprints differ."""
    return F.aggregate(F.zip_with(p, q, lambda a, b: F.bit_count(a.bitwiseXOR(b))), F.lit(0), lambda a, x: a + x)


def items(benchmark: DataFrame, gram: int = GRAM) -> DataFrame:
    """(item_id, words, n, hashes, numbered, weight, print) of the items that have words."""
    df = benchmark.select(F.col("item_id").cast("long"), words(F.col("text")).alias("words")).where(F.size("words") > 0)
    df = df.withColumns({"n": F.size("words"), "hashes": _hashes(F.col("words"), gram), "shingles": _shingles(F.col("words"), gram)})
    df = df.select("item_id", "words", "n", "hashes", _numbered(F.col("shingles")).alias("numbered"), F.size("hashes").alias("weight"))
    return df.withColumn("print", simhash(F.col("numbered")))


def _blocks(fingerprint: Column) -> Column:
    """The blocks of a fingerprint, each numbered in its upper bits."""
    return F.array(*[F.shiftrightunsigned(F.get(fingerprint, F.lit(b // 4)), 16 * (b % 4)).bitwiseAND(0xFFFF).cast("int") + (b << 16) for b in range(BLOCKS)])


def _flips(radius: int) -> list[int]:
    """Differences that one of the blocks shows at most where fingerprints are within the radius."""
    return [x for x in range(1 << 16) if x.bit_count() <= radius // BLOCKS]


def _item_keys(known: DataFrame, radius: int) -> DataFrame:
    """(n, block, item_id): every block value within reach of an item's own."""
    near = known.sparkSession.createDataFrame([(x,) for x in _flips(radius)], "flip int")
    blocks = known.select("n", "item_id", F.explode(_blocks(F.col("print"))).alias("b"))
    return blocks.crossJoin(F.broadcast(near)).select("n", "item_id", F.col("b").bitwiseXOR(F.col("flip")).alias("block"))


def _windows(docs: DataFrame, known: DataFrame, gram: int, threshold: float) -> DataFrame:
    """(doc_id, key, n, start, numbered, print, brief): item-sized windows that may reach the threshold, and the short items that each was laid for."""
    own = known.select("item_id", "n", "weight", F.posexplode("hashes").alias("j", "h"))
    every = known.agg(F.sum("weight")).first()[0] or 0
    base = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("key"))
    at = base.select("doc_id", "key", F.posexplode(_let(words(F.col("text")), lambda w: _hashes(w, gram))).alias("pos", "h"))
    hits = at.join(_small(own, every), "h").groupBy("doc_id", "key", "item_id", "n", "weight", "j", (F.col("pos") - F.col("j")).alias("start")).agg(F.lit(1).alias("x"))
    hits = settle(hits.drop("x"), "hits")
    # an item's shingles that stand in a document bound the similarity of any window of it
    enough = hits.groupBy("doc_id", "key", "item_id", "weight").agg(F.countDistinct("j").alias("held")).where(F.col("held") >= F.ceil(F.lit(threshold) * F.col("weight") - 1e-9))
    e = enough.select(F.col("doc_id").alias("d"), F.col("key").alias("k"), F.col("item_id").alias("i"))
    starts = hits.join(e, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k")) & (F.col("item_id") == F.col("i")))
    starts = starts.select("doc_id", "key", "n", "start", F.when(F.col("weight") < SHORT, F.col("item_id")).alias("brief")).distinct()
    laid = settle(starts.groupBy("doc_id", "key").agg(F.collect_list(F.struct("n", "start", "brief")).alias("laid")), "laid")
    few = _small(laid, laid.count())
    found = base.join(few, base["doc_id"].eqNullSafe(few["doc_id"]) & (base["key"] == few["key"])).select(base["doc_id"], base["key"], words(F.col("text")).alias("w"), "laid")
    found = settle(found.dropDuplicates(["doc_id", "key"]), "texts")
    spot = found.select("doc_id", "key", "w", F.explode("laid").alias("x")).select("doc_id", "key", "w", F.col("x.n").alias("n"), F.col("x.start").alias("want"), "x.brief")
    # a window stays inside its document
    spot = spot.select("doc_id", "key", "w", "n", F.greatest(F.lit(0), F.least(F.col("want"), F.size("w") - F.col("n"))).alias("start"), "brief")
    view = spot.groupBy("doc_id", "key", "n", "start").agg(F.first(F.slice("w", F.col("start") + 1, F.col("n"))).alias("v"), F.collect_set("brief").alias("brief"))
    view = view.select("doc_id", "key", "n", "start", "brief", _numbered_of(gram))
    view = settle(view.withColumn("print", F.when(F.size("numbered") >= threshold * SHORT, simhash(F.col("numbered")))), "windows")
    discard(hits, laid, found)
    return view


def candidates(view: DataFrame, known: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(doc_id, key, n, start, item_id): windows and items of their size whose fingerprints share a block within reach, or that are short."""
    tall = known.where(F.col("weight") >= SHORT)
    keyed = view.where("print is not null").select("doc_id", "key", "n", "start", F.explode(_blocks(F.col("print"))).alias("block"))
    met = keyed.join(_small(_item_keys(tall, radius), BLOCKS * len(_flips(radius)) * tall.count()), ["n", "block"]).drop("block")
    brief = view.select("doc_id", "key", "n", "start", F.explode("brief").alias("item_id"))
    return met.select("doc_id", "key", "n", "start", "item_id").union(brief).distinct()


def _matches(docs: DataFrame, benchmark: DataFrame, gram: int = GRAM, threshold: float = THRESHOLD, radius: int = RADIUS) -> DataFrame:
    """(doc_id, key, item_id, start, n, similarity) of the windows that reach the threshold."""
    known = settle(items(benchmark, gram), "items")
    view = _windows(docs, known, gram, threshold)
    v = view.select(F.col("doc_id").alias("d"), F.col("key").alias("k"), F.col("n").alias("m"), F.col("start").alias("s"), F.col("print").alias("p"), F.col("numbered").alias("a"))
    near = candidates(view, known, radius).join(v, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k")) & (F.col("n") == F.col("m")) & (F.col("start") == F.col("s")))
    near = near.join(_small(known.select("item_id", "weight", F.col("print").alias("q"), F.col("numbered").alias("b")), known.count()), "item_id")
    near = near.where((F.col("weight") < SHORT) | (distance(F.col("p"), F.col("q")) <= radius))
    shared = F.size(F.array_intersect("a", "b"))
    sim = shared / (F.size("a") + F.size("b") - shared)
    return near.select("doc_id", "key", "item_id", "start", "n", sim.alias("similarity")).where(F.col("similarity") >= threshold - 1e-12)


def search(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Matches of documents and items; see the module's text. Options: gram, threshold, radius."""
    best = _matches(docs, benchmark, **options).groupBy("doc_id", "item_id").agg(F.max(F.struct("similarity", (-F.col("start")).alias("s"), "n")).alias("x"))
    return best.select("doc_id", "item_id", (-F.col("x.s")).cast("long").alias("start"), F.col("x.n").cast("long").alias("n_words"), F.round("x.similarity", 6).alias("similarity"))


def _numbered_of(gram: int) -> Column:
    return _let(_shingles(F.col("v"), gram), _numbered).alias("numbered")


def clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """``docs`` without the rows whose own text holds a benchmark item, whatever their doc_id."""
    held = _matches(docs, benchmark, **options).select("doc_id", "key").distinct().select(F.col("doc_id").alias("__d"), F.col("key").alias("__k"))
    x = docs.select(F.struct("*").alias("__row"), F.col("doc_id").cast("long").alias("__doc"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("__key"))
    return x.join(held, F.col("__doc").eqNullSafe(F.col("__d")) & (F.col("__key") == F.col("__k")), "left_anti").select("__row.*")
