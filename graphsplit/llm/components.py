"""Connected components of an edge table, by hooking to the smallest neighbour and contracting.

Each round: every node takes the least of itself and its neighbours, pointers are followed to the roots, edges are renamed
and loops and repeats dropped.  Renaming shrinks the edges fast; a chain of any length ends after a logarithmic number of rounds.
Groupings have partial sums and joins are skew-splittable, so a node with a third of all edges is no hot task.  Each round's
tables are written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage


def connected(edges: DataFrame) -> DataFrame:
    """(node, component): the least node that can be reached, for all nodes with an edge to another; input columns a, b (long)."""
    pairs = edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = storage.spill(pairs, "edges")
    total = None
    while pairs.take(1):
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = storage.spill(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("p")).withColumnRenamed("a", "v"), "hooks")
        # Follow pointers to the roots; each step halves the trees' depth, and most trees are stars.
        while True:
            at = up.select(F.col("v").alias("w"), F.col("p").alias("q"))
            jumped = storage.spill(up.join(at, up["p"] == at["w"], "left").select("v", F.coalesce("q", "p").alias("p"), (F.coalesce("q", "p") != F.col("p")).alias("moved")), "pointers")
            storage.release(up)
            more = bool(jumped.where("moved").take(1))
            path, up = jumped._spilled_at, jumped.drop("moved")
            up._spilled_at = path
            if not more:
                break
        a, b = up.select(F.col("v").alias("a"), F.col("p").alias("pa")), up.select(F.col("v").alias("b"), F.col("p").alias("pb"))
        renamed = pairs.join(a, "a").join(b, "b").where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct()
        new_pairs = storage.spill(renamed, "edges")
        if total is None:
            new_total = up
        else:
            step = up.select(F.col("v").alias("w"), F.col("p").alias("q"))
            new_total = storage.spill(total.join(step, total["p"] == step["w"], "left").select("v", F.coalesce("q", "p").alias("p")), "labels")
            storage.release(total, up)
        storage.release(pairs)
        pairs, total = new_pairs, new_total
    if total is None:
        return edges.select(F.col("a").alias("node"), F.col("a").alias("component")).limit(0)
    return total.select(F.col("v").alias("node"), F.col("p").alias("component"))
