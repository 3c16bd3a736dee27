"""SQL functions, table functions, and an estimator."""

from __future__ import annotations

import numpy as np
from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from .functions.hashing import mix_sql
from .operators import local
from .operators.local import Options

#: SQL functions without Python: name -> (parameters, return type, body).
FUNCTIONS = {
    "limit_relaxed": ("total DOUBLE, k INT, eps DOUBLE, top DOUBLE", "DOUBLE", "greatest((1 + eps) * total / k, total / k + top)"),
    "limit_strict": ("total DOUBLE, k INT, eps DOUBLE", "DOUBLE", "(1 + eps) * ceil(total / k)"),
    "eps_adaptive": ("eps DOUBLE, total DOUBLE, k INT, part DOUBLE, parts INT", "DOUBLE", "case when parts <= 1 then 0.0D else greatest(0.0D, power((1 + eps) * total / k * parts / part, 1 / ceil(log2(parts))) - 1) end"),
    "ceil2": ("x BIGINT", "BIGINT", "case when x <= 1 then 1L else cast(power(2, length(bin(x - 1))) as bigint) end"),
    "floor2": ("x BIGINT", "BIGINT", "cast(power(2, length(bin(x)) - 1) as bigint)"),
    "relative_gain": ("d DOUBLE, c DOUBLE", "DOUBLE", "case when d >= 0 then d * c else d / c end"),
    "split_mix": ("x BIGINT", "BIGINT", mix_sql("x", 0)),
}


@udtf(returnType="neighbor: bigint, w: bigint")
class Neighbors:
    """The entries of an adjacency text "id:w,id:w"."""

    def eval(self, adj: str):
        for item in (adj or "").split(","):
            if item:
                a, b = item.split(":")
                yield int(a), int(b)


@udtf(returnType="id: bigint, block: int")
class PartitionGraph:
    """``SELECT * FROM partition_graph(TABLE(edges) WITH SINGLE PARTITION, k, eps, scheme)`` for graphs that fit a task."""

    def __init__(self):
        self.rows, self.spec = [], (2, 0.03, "one_cycle")

    def eval(self, row, k: int, eps: float = 0.03, scheme: str = "one_cycle"):
        self.rows.append((row["src"], row["dst"], row["w"]))
        self.spec = (k, eps, scheme)

    def terminate(self):
        if not self.rows:
            return
        e = np.array(self.rows, dtype=np.int64)
        ids = np.unique(e[:, :2])
        a, b = np.searchsorted(ids, e[:, 0]), np.searchsorted(ids, e[:, 1])
        keep = a != b
        low, high = np.minimum(a, b)[keep], np.maximum(a, b)[keep]
        key, inverse = np.unique(low * len(ids) + high, return_inverse=True)
        w = np.bincount(inverse, weights=e[keep, 2]).astype(np.int64)
        x, y = key // len(ids), key % len(ids)
        g = local.Csr(np.ones(len(ids)), np.r_[x, y], np.r_[y, x], np.r_[w, w])
        k, eps, scheme = self.spec
        for i, block in zip(ids.tolist(), local.SCHEMES[scheme](g, k, Options(eps=eps)).tolist(), strict=True):
            yield i, block


def register(spark: SparkSession) -> None:
    for name, (params, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("neighbors", Neighbors)
    spark.udtf.register("partition_graph", PartitionGraph)


class GraphSplitterModel(Model):
    """Adds the column block to a frame with id."""

    def __init__(self, part: DataFrame):
        super().__init__()
        self.part = part

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return dataset.join(self.part, "id", "left")


class GraphSplitter(Estimator):
    """``GraphSplitter(k, eps).fit(edges).transform(nodes)``; edges have src, dst, w."""

    def __init__(self, k: int, eps: float = 0.03, options: Options | None = None):
        super().__init__()
        self.k, self.options = k, options or Options(c=2000)
        self.options.eps = eps

    def _fit(self, dataset: DataFrame) -> GraphSplitterModel:
        from .model import from_edges
        from .plans.partitioner import partition
        from .storage import spill

        return GraphSplitterModel(spill(partition(from_edges(dataset), self.k, self.options), "fitted"))


def blocks_view(spark: SparkSession, part: DataFrame, edges: DataFrame) -> None:
    """Views ``blocks`` (block, n) and ``cut_edges`` (src, dst, w) of a partition."""
    part.groupBy("block").agg(F.count(F.lit(1)).alias("n")).createOrReplaceTempView("blocks")
    a, b = part.select(F.col("id").alias("src"), F.col("block").alias("bs")), part.select(F.col("id").alias("dst"), F.col("block").alias("bd"))
    edges.join(a, "src").join(b, "dst").where("bs <> bd").select("src", "dst", "w").createOrReplaceTempView("cut_edges")
