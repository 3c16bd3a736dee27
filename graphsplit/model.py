"""The data model: a weighted undirected graph as two frames, its facts, and its checks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class Facts:
    """Scalars of a graph: nodes, undirected edges, node weight, heaviest node, edge weight."""

    n: int
    m: int
    weight: int
    heaviest: int
    edge_weight: int


@dataclass
class SplitGraph:
    """nodes (id, w) and edges (src, dst, w) in both directions, without loops, one row for each ordered pair."""

    nodes: DataFrame
    edges: DataFrame
    _facts: Facts | None = None

    @property
    def facts(self) -> Facts:
        if self._facts is None:
            a = self.nodes.agg(F.count(F.lit(1)), F.sum("w"), F.max("w")).first()
            b = self.edges.agg(F.count(F.lit(1)), F.sum("w")).first()
            self._facts = Facts(a[0], b[0] // 2, a[1] or 0, a[2] or 0, (b[1] or 0) // 2)
        return self._facts

    def undirected(self) -> DataFrame:
        return self.edges.where("src < dst")


def both_ways(pairs: DataFrame) -> DataFrame:
    """Each undirected edge as two rows, without a second scan."""
    return pairs.select(F.explode(F.array(F.struct(F.col("src"), F.col("dst"), F.col("w")), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("w")))).alias("e")).select("e.*")


def canonical(df: DataFrame, src: str = "src", dst: str = "dst", w: str | None = "w") -> DataFrame:
    """Undirected pairs with src < dst: loops dropped, parallel edges summed."""
    weight = F.col(w).cast("long") if w else F.lit(1).cast("long")
    pairs = df.where(F.col(src) != F.col(dst)).select(F.least(src, dst).cast("long").alias("src"), F.greatest(src, dst).cast("long").alias("dst"), weight.alias("w"))
    return pairs.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def from_edges(df: DataFrame, src: str = "src", dst: str = "dst", w: str | None = "w", nodes: DataFrame | None = None, node_w: str | None = None) -> SplitGraph:
    """A graph from an edge table of any direction; nodes from ``nodes`` (id and weight ``node_w``), else from the edges, with weight 1.

    ``node_w='degree'`` weighs nodes by their number of neighbours.
    """
    edges = both_ways(canonical(df, src, dst, w))
    if nodes is None:
        found = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
        return SplitGraph(found.select("id", (F.col("d") if node_w == "degree" else F.lit(1).cast("long")).alias("w")), edges)
    own = nodes.select(F.col("id").cast("long"), (F.col(node_w).cast("long") if node_w and node_w != "degree" else F.lit(1).cast("long")).alias("w"))
    if node_w == "degree":
        d = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
        own = own.drop("w").join(d, "id", "left").select("id", F.greatest(F.coalesce("d", F.lit(0)), F.lit(1)).cast("long").alias("w"))
    return SplitGraph(own, edges)


def faults(g: SplitGraph) -> DataFrame:
    """(check, rows): how many rows break each rule of the model; all zero for a valid graph."""
    e, n = g.edges, g.nodes
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    checks = {
        "node null or light": n.where("id is null or w is null or w < 1"),
        "node twice": n.groupBy("id").count().where("count > 1"),
        "edge null or light": e.where("src is null or dst is null or w is null or w < 1"),
        "loop": e.where("src = dst"),
        "pair twice": e.groupBy("src", "dst").count().where("count > 1"),
        "one way only": e.join(back, ["src", "dst", "w"], "left_anti"),
        "end is no node": e.join(n.select(F.col("id").alias("src")), "src", "left_anti"),
    }
    out = None
    for name, bad in checks.items():
        row = bad.agg(F.count(F.lit(1)).alias("rows")).select(F.lit(name).alias("check"), "rows")
        out = row if out is None else out.unionByName(row)
    return out
