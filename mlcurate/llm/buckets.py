"""Candidate pairs from bucket rows without writing out all pairs of a bucket.

``members`` keeps the rows (key, id) of buckets with two ids or more, one of those that hold the
same ids, and adds the bucket's smallest id, its pivot. ``star`` pairs every member with the pivot. Once
star pairs say which ids belong together, ``mixed`` keeps the buckets that still hold
ids of different groups. ``blocks`` deals the rows of a bucket, whatever its size, into
blocks of bounded size and sends each pair of blocks to one task, so pairs are looked
at inside a task and never written out as rows. The largest group of a bucket gets blocks
of its own, which are never paired with each other.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.session import discard, release, settle

#: Buckets of a table that are sent to every executor at most (16 MB).
BROADCAST_ROWS = 1_000_000
MOST_PASSES = 16
#: What tells buckets by the ids that they hold.
SAME = ("pivot", "far", "n", "ids")


def members(*parts: DataFrame) -> DataFrame:
    """(key, id, pivot, n) of the buckets with n ids, two or more, settled. Rows (key, id) are distinct. Parts hold different keys and are
    dealt one after the other, so that the shuffles of one part at a time are on disk. A part is read twice: minima combine before the
    shuffle, so no bucket is one task's, and few buckets are joined without another shuffle. Of buckets that hold the same ids, as those
    of near copies do in most bands, one is kept: the others say nothing new. They are told by n, their ends and the ids' combined hashes."""
    found, seen = [], []
    for rows in parts:
        ends = rows.groupBy("key").agg(F.min("id").alias("pivot"), F.max("id").alias("far"), F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("id")).alias("ids")).where("pivot != far")
        once = ends.groupBy(*SAME).agg(F.min("key").alias("key"))
        if seen:
            once = once.join(reduce(DataFrame.union, seen).select(*SAME), list(SAME), "left_anti")
        once = settle(once, "pivots")
        few = once.select("key", "pivot", "n")
        found.append(settle(rows.join(F.broadcast(few) if once.count() <= BROADCAST_ROWS else few, "key"), "buckets"))
        if len(parts) > 1:
            release(rows.sparkSession)
        seen.append(once)
    discard(*seen)
    return joined(found, "buckets")


def joined(parts: list[DataFrame], name: str) -> DataFrame:
    """One settled table of several, which are deleted."""
    if len(parts) == 1:
        return parts[0]
    out = settle(reduce(DataFrame.union, parts), name)
    discard(*parts)
    return out


def passes(rows: int, most: int) -> int:
    """How often a step runs over parts of its rows, so that a part has about ``most`` of them; ``MOST_PASSES`` bounds it."""
    return min(max(-(-rows // most), 1), MOST_PASSES)


def star(m: DataFrame) -> DataFrame:
    """(a, b) with a < b: every member and its bucket's pivot, each pair once."""
    return m.where("id != pivot").select(F.col("pivot").alias("a"), F.col("id").alias("b")).distinct()


def mixed(m: DataFrame, groups: DataFrame) -> DataFrame:
    """(key, id, grp): members of the buckets that hold more than one group.

    groups: (id, grp); an id without a row is a group of its own."""
    g = m.join(groups, "id", "left").select("key", "id", F.coalesce("grp", "id").alias("grp"))
    some = g.groupBy("key").agg(F.min("grp").alias("lo"), F.max("grp").alias("hi")).where("lo != hi").select("key")
    return g.join(some, "key", "left_semi")


def blocks(rows: DataFrame, bucket: str, group: str, size: Column, most: int) -> DataFrame:
    """``rows`` with columns lo, hi and block: each row once for every pair of blocks that its own is in.

    ``size`` is what a row weighs; a block weighs about ``most``. Only pairs of different groups matter. So the
    blocks of a bucket's largest group meet the blocks of the rest but not each other: a row of it is copied as
    often as there are blocks of the rest, however large its group is."""
    part = rows.groupBy(F.col(bucket).alias("__b"), F.col(group).alias("__g")).agg(F.sum(size).alias("__w"))
    n = part.groupBy("__b").agg(F.max(F.struct("__w", "__g")).alias("__top"), F.sum("__w").alias("__all"))
    many = lambda w: F.ceil(w / most).cast("int")
    n = settle(n.select("__b", F.col("__top.__g").alias("__g"), many(F.col("__top.__w")).alias("__big"), many(F.col("__all") - F.col("__top.__w")).alias("__rest")), "dealt")
    x = rows.join(F.broadcast(n) if n.count() <= BROADCAST_ROWS else n, F.col(bucket) == F.col("__b"))
    first = F.col(group) == F.col("__g")
    hashed = lambda k: F.pmod(F.xxhash64("id"), k).cast("int")
    x = x.withColumn("block", F.when(first, hashed(F.col("__big"))).otherwise(F.col("__big") + hashed(F.greatest(F.col("__rest"), F.lit(1)))))
    x = x.withColumn("__x", F.explode(F.sequence(F.when(first, F.col("__big")).otherwise(0), F.col("__big") + F.col("__rest") - 1)))
    return x.withColumns({"lo": F.least("block", "__x"), "hi": F.greatest("block", "__x")}).drop("__b", "__g", "__big", "__rest", "__x")
