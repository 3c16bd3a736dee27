"""What is measured on a partition: cut, balance, feasibility, boundary, communication; and certificates."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import rules
from ..functions.hashing import mix
from ..model import SplitGraph
from ..storage import small, spill


def both_blocks(pairs: DataFrame, part: DataFrame, hint: str | None = None) -> DataFrame:
    """Edges with the blocks of their ends, bs and bd; ``hint`` names a join strategy (merge, shuffle_hash) where Spark's own choice is not wanted."""
    part = part.hint(hint) if hint else part
    a, b = part.select(F.col("id").alias("src"), F.col("block").alias("bs")), part.select(F.col("id").alias("dst"), F.col("block").alias("bd"))
    return pairs.join(a, "src").join(b, "dst")


def edge_cut(g: SplitGraph, part: DataFrame, hint: str | None = None) -> DataFrame:
    """(cut): weight of the edges between blocks."""
    return both_blocks(g.undirected(), part, hint).agg(F.coalesce(F.sum(F.when(F.col("bs") != F.col("bd"), F.col("w"))), F.lit(0)).alias("cut"))


def block_weights(g: SplitGraph, part: DataFrame) -> DataFrame:
    return g.nodes.join(part, "id").groupBy("block").agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))


def imbalance(g: SplitGraph, part: DataFrame, k: int) -> DataFrame:
    """(imbalance): the heaviest block over the average of k."""
    return block_weights(g, part).agg((F.max("w") * k / F.sum("w")).alias("imbalance"))


def is_feasible(g: SplitGraph, part: DataFrame, k: int, eps: float, rule: str = "relaxed") -> DataFrame:
    """(feasible, heaviest_block, cap) under the relaxed or the traditional limit."""
    f = g.nodes.agg(F.sum("w").alias("total"), F.max("w").alias("top"))
    cap = F.greatest(F.lit(1 + eps) * F.col("total") / k, F.col("total") / k + F.col("top")) if rule == "relaxed" else F.lit(1 + eps) * F.ceil(F.col("total") / k)
    top = block_weights(g, part).agg(F.max("w").alias("heaviest_block"))
    return top.crossJoin(F.broadcast(f)).select((F.col("heaviest_block") <= cap).alias("feasible"), "heaviest_block", cap.alias("cap"))


def quotient(g: SplitGraph, part: DataFrame) -> DataFrame:
    """(a, b, w): weight between each pair of blocks."""
    cut = both_blocks(g.undirected(), part).where("bs <> bd")
    return cut.groupBy(F.least("bs", "bd").alias("a"), F.greatest("bs", "bd").alias("b")).agg(F.sum("w").alias("w"))


def boundary(g: SplitGraph, part: DataFrame) -> DataFrame:
    """(id): nodes with a neighbour in another block."""
    return both_blocks(g.edges, part).where("bs <> bd").select(F.col("src").alias("id")).distinct()


def external_degree(g: SplitGraph, part: DataFrame) -> DataFrame:
    """(block, external): for each block, the weight of its edges to others."""
    return both_blocks(g.edges, part).where("bs <> bd").groupBy(F.col("bs").alias("block")).agg(F.sum("w").alias("external"))


def comm_volume(g: SplitGraph, part: DataFrame) -> DataFrame:
    """(block, volume): for each block, the sum over its nodes of the other blocks they have neighbours in."""
    far = both_blocks(g.edges, part).where("bs <> bd").select("src", F.col("bs").alias("block"), "bd").distinct()
    return far.groupBy("block").agg(F.count(F.lit(1)).alias("volume"))


def diff(one: DataFrame, two: DataFrame) -> DataFrame:
    """(old, new, n): how many nodes go from which block to which; nodes of one side only have null on the other."""
    return one.withColumnRenamed("block", "old").join(two.withColumnRenamed("block", "new"), "id", "full").groupBy("old", "new").agg(F.count(F.lit(1)).alias("n"))


def match_labels(nodes: DataFrame, old: DataFrame, new: DataFrame) -> DataFrame:
    """(id, block): ``new`` with its blocks renamed to blocks of ``old`` of large common weight, so that a re-run moves little.

    Block pairs that are each other's heaviest are matched, round by round until no common weight is left; their weight is at least half of the
    best matching's.  Blocks that are left over get the free names in order.  Work on nodes is one join; the rounds see pairs of blocks only.
    """
    pairs = nodes.join(old.select("id", F.col("block").alias("a")), "id").join(new.select("id", F.col("block").alias("b")), "id")
    left = spill(pairs.groupBy("a", "b").agg(F.sum("w").alias("w")), "overlap")
    named = None
    while left.take(1):
        best_a = left.groupBy("a").agg(F.max_by("b", F.struct("w", -F.col("a"), -F.col("b"))).alias("b"))
        best_b = left.groupBy("b").agg(F.max_by("a", F.struct("w", -F.col("a"), -F.col("b"))).alias("a"))
        found = spill(best_a.join(best_b, ["a", "b"]), "matched")
        named = found if named is None else spill(named.unionByName(found), "names")
        left = spill(left.join(found.select("a"), "a", "left_anti").join(found.select("b"), "b", "left_anti"), "overlap")
    blocks = new.select(F.col("block").alias("b")).distinct()
    if named is None:
        return new.select("id", "block")
    rank = lambda c: F.row_number().over(W.orderBy(c)).alias("r")
    spare = blocks.join(named, "b", "left_anti").select("b", rank("b"))
    every = blocks.select(F.col("b").alias("a")).unionByName(old.select(F.col("block").alias("a"))).distinct()
    free = every.join(named, "a", "left_anti").select("a", rank("a"))
    names = spill(named.select("a", "b").unionByName(spare.join(free, "r").select("a", "b")), "names")
    return new.join(small(names.withColumnRenamed("b", "block")), "block").select("id", F.col("a").alias("block"))


def inner_weights(g: SplitGraph, part: DataFrame) -> DataFrame:
    """(block, n, inner): nodes of each block and the weight of the edges inside it, from the co-grouped frames of nodes and edges.

    Both frames come as partial counts (block, slice), so no group grows with its block.
    """
    nodes = part.groupBy("block", (mix("id", 3) % 64).alias("s")).agg(F.count(F.lit(1)).alias("n"))
    edges = both_blocks(g.undirected(), part).where("bs = bd").withColumnRenamed("bs", "block").groupBy("block", (mix("src", 3) % 64).alias("s")).agg(F.sum("w").alias("w"))

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        return pa.table({"block": [key[0].as_py()], "n": [pc.sum(left["n"]).as_py() or 0], "inner": [pc.sum(right["w"]).as_py() or 0]}, schema=pa.schema([("block", pa.int32()), ("n", pa.int64()), ("inner", pa.int64())]))

    return nodes.groupBy("block").cogroup(edges.groupBy("block")).applyInArrow(run, "block int, n long, inner long")


def describe_graph(g: SplitGraph) -> DataFrame:
    """(n, m, w, max_deg)."""
    d = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"), F.sum("w").alias("w"))
    edges = d.agg((F.coalesce(F.sum("d"), F.lit(0)) / 2).cast("long").alias("m"), (F.coalesce(F.sum("w"), F.lit(0)) / 2).cast("long").alias("w"), F.coalesce(F.max("d"), F.lit(0)).alias("max_deg"))
    return g.nodes.agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(edges))


def certify(g: SplitGraph, part: DataFrame, k: int, eps: float = 0.03, mod: DataFrame | None = None) -> DataFrame:
    """(metric, value): facts that any correct partition shows, computed from the graph and the partition alone.

    over_relaxed counts blocks above the relaxed limit; cut_le_mod is 1 if the cut is no larger than that of ``mod``.
    """
    cut = both_blocks(g.undirected(), part.join(mod.withColumnRenamed("block", "other"), "id") if mod is not None else part)
    if mod is not None:
        a, b = mod.select(F.col("id").alias("src"), F.col("block").alias("ms")), mod.select(F.col("id").alias("dst"), F.col("block").alias("md"))
        cut = both_blocks(g.undirected(), part).join(a, "src").join(b, "dst")
    else:
        cut = both_blocks(g.undirected(), part).withColumn("ms", F.lit(0)).withColumn("md", F.lit(1))
    edges = cut.agg(
        F.coalesce(F.sum("w"), F.lit(0)).alias("edge_weight"), F.coalesce(F.sum(F.when(F.col("bs") != F.col("bd"), F.col("w"))), F.lit(0)).alias("cut"),
        F.coalesce(F.sum(F.when(F.col("ms") != F.col("md"), F.col("w"))), F.lit(0)).alias("mod_cut"), F.coalesce(F.sum(F.when(F.col("bs") == F.col("bd"), F.col("w"))), F.lit(0)).alias("inner"),
    )
    facts = g.nodes.agg(F.count(F.lit(1)).alias("nodes"), F.sum("w").alias("node_weight"), F.max("w").alias("top"))
    own = part.agg(F.count(F.lit(1)).alias("assigned"), F.count_distinct("id").alias("distinct_ids"), F.count_distinct("block").alias("blocks_used"), F.min("block").alias("low"), F.max("block").alias("high"))
    limit = F.greatest(F.lit(1 + eps) * F.col("node_weight") / k, F.col("node_weight") / k + F.col("top"))
    over = block_weights(g, part).select("w").crossJoin(F.broadcast(facts)).agg(F.count_if(F.col("w") > limit + 1e-6).alias("over_relaxed"))
    one = edges.crossJoin(facts).crossJoin(own).crossJoin(over)
    values = {
        "nodes": F.col("nodes"), "assigned": F.col("assigned"), "distinct_ids": F.col("distinct_ids"), "blocks_used": F.col("blocks_used"), "blocks_in_range": ((F.col("low") >= 0) & (F.col("high") < k)).cast("long"),
        "node_weight": F.col("node_weight"), "edge_weight": F.col("edge_weight"), "over_relaxed": F.col("over_relaxed"), "cut_le_mod": (F.col("cut") <= F.col("mod_cut")).cast("long"),
        "cut_plus_inner_ok": (F.col("cut") + F.col("inner") == F.col("edge_weight")).cast("long"),
    }
    return one.select(F.explode(F.array(*[F.struct(F.lit(m).alias("metric"), v.cast("long").alias("value")) for m, v in values.items()])).alias("r")).select("r.*")


def certify_many(g: SplitGraph, parts: DataFrame, instances: list[dict], eps: float = 0.03) -> DataFrame:
    """The same for the frame (inst, id, block) of ``partition_many``, with scheme and k: one plan for all instances."""
    spark = g.nodes.sparkSession
    table = F.broadcast(spark.createDataFrame([(i, s.get("name", s.get("scheme", "one_cycle")), s["k"], float(s.get("eps", eps))) for i, s in enumerate(instances)], "inst int, scheme string, k int, eps double"))
    facts = F.broadcast(g.nodes.agg(F.count(F.lit(1)).alias("nodes"), F.sum("w").alias("node_weight"), F.max("w").alias("top")))
    # An edge meets the blocks of all instances at once: a node has one row, with a block for each instance.
    names = range(len(instances))
    blocks = parts.groupBy("id").agg(*[F.max(F.when(F.col("inst") == i, F.col("block"))).alias(f"b{i}") for i in names])
    one, two = (blocks.select(F.col("id").alias(end), F.struct(*[f"b{i}" for i in names]).alias(f"_{end}")) for end in ("src", "dst"))
    differ = lambda a, b: F.coalesce(F.sum(F.when(a != b, F.col("w"))), F.lit(0))
    sums = []
    for i, spec in enumerate(instances):
        a, b, k = F.col(f"_src.b{i}"), F.col(f"_dst.b{i}"), F.lit(spec["k"])
        sums.append(F.struct(
            F.lit(i).alias("inst"), F.sum(F.when(a.isNotNull() & b.isNotNull(), F.col("w"))).alias("edge_weight"), differ(a, b).alias("cut"),
            F.coalesce(F.sum(F.when(a.isNotNull() & b.isNotNull() & (F.col("src") % k != F.col("dst") % k), F.col("w"))), F.lit(0)).alias("mod_cut"),
        ))
    edges = g.undirected().join(one, "src").join(two, "dst").agg(F.array(*sums).alias("found")).select(F.inline("found")).where("edge_weight is not null")
    own = parts.groupBy("inst").agg(F.count(F.lit(1)).alias("assigned"), F.count_distinct("id").alias("distinct_ids"), F.count_distinct("block").alias("blocks_used"))
    weights = parts.join(g.nodes, "id").groupBy("inst", "block").agg(F.sum("w").alias("bw"))
    limit = F.greatest((1 + F.col("eps")) * F.col("node_weight") / F.col("k"), F.col("node_weight") / F.col("k") + F.col("top"))
    over = weights.join(table, "inst").crossJoin(facts).groupBy("inst").agg(F.count_if(F.col("bw") > limit + 1e-6).alias("over_relaxed"), F.max("bw").alias("max_block_w"))
    return table.join(own, "inst").join(over, "inst").join(edges, "inst", "left").crossJoin(facts)


def runs_of(certified: DataFrame, graph: str) -> DataFrame:
    """Rows (algo, graph, k, cut, max_block_w, over_relaxed) of ``certify_many``."""
    return certified.select(F.col("scheme").alias("algo"), F.lit(graph).alias("graph"), "k", "cut", "max_block_w", "over_relaxed")


def limits(total: int, k: int, eps: float, heaviest: int) -> dict[str, float]:
    return {"relaxed": rules.limit_relaxed(total, k, eps, heaviest), "strict": rules.limit_strict(total, k, eps)}
