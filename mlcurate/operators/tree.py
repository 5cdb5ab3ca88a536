"""Proxy tokenizers over a language-family tree.

Upward, each family takes per script, of its children's tokenizers, the one whose
language has most data; the root takes none. Downward, a language without its own
tokenizer takes that of its nearest ancestor that has one for its script. Trees are
small (thousands of nodes), so levels are a loop over plans.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.session import settle


def assign(nodes: DataFrame, shared: dict[str, str] | None = None, by_script: bool = False) -> DataFrame:
    """(node, script, tokenizer, via) of the leaves.

    nodes: node, parent (null: root), script (null: a family), tokenizer (null: none), size.
    ``shared`` gives a tokenizer to scripts for what the tree leaves without; with ``by_script``
    what is left takes the tokenizer of the largest language in its script."""
    edges = nodes.select("node", "parent")
    roots = [r[0] for r in nodes.where("parent is null").select("node").collect()]
    have = nodes.where("tokenizer is not null and script is not null").select("node", "script", "tokenizer", F.col("size").cast("long").alias("size"))
    up = every = have
    while True:  # a round per level of the tree
        up = up.join(edges, "node").where(F.col("parent").isNotNull() & ~F.col("parent").isin(roots)).select(F.col("parent").alias("node"), "script", "tokenizer", "size")
        up = up.groupBy("node", "script").agg(F.max(F.struct("size", "tokenizer")).alias("b")).select("node", "script", "b.tokenizer", "b.size")
        up = settle(up, "tree")
        if up.isEmpty():
            break
        every = every.unionByName(up)
    best = settle(every.groupBy("node", "script").agg(F.max_by("tokenizer", F.struct("size", "tokenizer")).alias("tokenizer")), "tree")
    leaves = nodes.where("script is not null").select("node", "script", F.col("node").alias("at"), F.lit(0).alias("steps"), "size")
    found = settle(leaves.join(best.withColumnRenamed("node", "at"), ["at", "script"], "left"), "tree")
    done, open_ = found.where("tokenizer is not null"), found.where("tokenizer is null").drop("tokenizer")
    while not open_.isEmpty():
        nxt = open_.join(edges.select(F.col("node").alias("at"), F.col("parent").alias("above")), "at").where(F.col("above").isNotNull() & ~F.col("above").isin(roots))
        nxt = nxt.select("node", "script", F.col("above").alias("at"), (F.col("steps") + 1).alias("steps"), "size")
        found = settle(nxt.join(best.withColumnRenamed("node", "at"), ["at", "script"], "left"), "tree")
        done, open_ = done.unionByName(found.where("tokenizer is not null").select(done.columns)), found.where("tokenizer is null").drop("tokenizer")
    got = nodes.where("script is not null").select("node", "script", "size").join(done.select("node", "tokenizer", F.col("at")), "node", "left")
    via = F.when(F.col("at") == F.col("node"), "native").when(F.col("at").isNotNull(), F.col("at").cast("string"))
    out = got.select("node", "script", "tokenizer", via.alias("via"))
    for s, t in (shared or {}).items():
        miss = F.col("tokenizer").isNull() & (F.col("script") == s)
        out = out.select("node", "script", F.when(miss, t).otherwise(F.col("tokenizer")).alias("tokenizer"), F.when(miss, "shared").otherwise(F.col("via")).alias("via"))
    if by_script:
        big = have.groupBy("script").agg(F.max_by("tokenizer", F.struct("size", "tokenizer")).alias("own"))
        out = out.join(F.broadcast(big), "script", "left").select("node", "script", F.coalesce("tokenizer", "own").alias("tokenizer"), F.coalesce("via", F.when(F.col("own").isNotNull(), "script")).alias("via"))
    return out
