"""Connected components by alternating star contraction, or by spreading minima.

Every round is a grouped minimum (combined before the shuffle) and a join; nothing
gathers a node's neighbours in one place, so hubs cost no more than their edges.
Each round's edges are written to the shared folder, which cuts lineage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.session import discard, settle

#: A chain of n nodes needs about log2 n rounds; more means a defect.
MOST_ROUNDS = 60


def _large_star(e: DataFrame) -> DataFrame:
    """Each node links its larger neighbours to its smallest neighbour (or itself)."""
    both = e.union(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    least = both.groupBy("src").agg(F.least(F.min("dst"), F.col("src")).alias("m"))
    return both.where("dst > src").join(least, "src").select(F.col("dst").alias("src"), F.col("m").alias("dst"))


def _small_star(e: DataFrame) -> DataFrame:
    """Each node links itself and its smaller neighbours to the smallest of them. Edges point from larger to smaller."""
    least = e.groupBy("src").agg(F.min("dst").alias("m"))
    x = e.join(least, "src")
    return x.select(F.col("dst").alias("src"), F.col("m").alias("dst")).union(x.select("src", F.col("m").alias("dst"))).where("src != dst").distinct()


def connected(edges: DataFrame, algo: str = "star") -> DataFrame:
    """(id, comp): comp is the smallest id that a node reaches over ``edges`` (src, dst), in either direction.

    Self-loops and repeated edges do no harm; nodes without an edge don't appear; null ends are ignored."""
    e = edges.where("src is not null and dst is not null and src != dst").select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct()
    e = settle(e, "edges")
    return _by_minima(e) if algo == "minlabel" else _by_stars(e)


def _mark(e: DataFrame) -> tuple:
    return tuple(e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("src", "dst")), F.sum(F.xxhash64("dst", "src").cast("decimal(20,0)"))).first())


def _by_stars(e: DataFrame) -> DataFrame:
    before = _mark(e)
    for _ in range(MOST_ROUNDS):
        if not before[0]:
            break
        last, e = e, settle(_small_star(_large_star(e)), "edges")
        after = _mark(e)
        discard(last)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("src").alias("id"), F.col("dst").alias("comp")).union(e.select(F.col("dst").alias("id"), F.col("dst").alias("comp")).distinct())


def _by_minima(e: DataFrame) -> DataFrame:
    both = e.union(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    labels = settle(both.groupBy(F.col("src").alias("id")).agg(F.least(F.min("dst"), F.col("src")).alias("comp")), "labels")
    for _ in range(10_000):
        spread = both.join(labels.select("id", "comp"), F.col("dst") == F.col("id")).groupBy("src").agg(F.min("comp").alias("near")).withColumnRenamed("src", "id")
        new = settle(labels.select("id", "comp").join(spread, "id").select("id", F.least("comp", "near").alias("comp"), (F.col("near") < F.col("comp")).alias("moved")), "labels")
        moved = new.where("moved").limit(1).count()
        discard(labels)
        if not moved:
            return new.drop("moved")
        labels = new
    raise RuntimeError("labels did not settle")
