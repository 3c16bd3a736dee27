"""Graph files: adjacency text, coordinate text, edge lists; and sinks for graphs and partitions.

Adjacency text: a header "n m [fmt]" and then a line of neighbours for each node, numbered from 1; fmt 1 has edge weights, 10 node
weights, 11 both.  Coordinate text: comment lines, a header "rows cols entries", then "i j [w]" lines.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model import SplitGraph, canonical, from_edges
from ..storage import small


def read_edge_csv(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    return canonical(spark.read.csv(path, sep=sep, schema="src long, dst long, w long"))


def write_edge_csv(pairs: DataFrame, path: str) -> None:
    pairs.select("src", "dst", "w").write.csv(path)


def read_edge_json(spark: SparkSession, path: str) -> DataFrame:
    return canonical(spark.read.json(path, schema="src long, dst long, w long"))


def read_coordinate(spark: SparkSession, path: str) -> DataFrame:
    """Pairs of a symmetric matrix's entries; ids from 1 become ids from 0.

    The header is the first line that is no comment of the file whose name sorts first, whatever order the files are scheduled in;
    a body with another number of entries than it names raises ``ValueError``.
    """
    lines = spark.read.text(path).where(~F.col("value").startswith("%") & (F.trim("value") != ""))
    place = F.struct("_metadata.file_path", "_metadata.file_block_start", F.monotonically_increasing_id().alias("row"))
    parts = lines.select(F.split(F.trim("value"), r"\s+").alias("p"), place.alias("at"))
    head = parts.agg(F.min_by("p", "at").alias("p"), F.min("at").alias("at"), (F.count(F.lit(1)) - 1).alias("entries")).first()
    if head.p is None or len(head.p) < 3 or int(head.p[2]) != head.entries:
        raise ValueError(f"the header {head.p} does not name {head.entries} entries")
    body = parts.where(~((F.col("at.file_path") == head.at[0]) & (F.col("at.file_block_start") == head.at[1]) & (F.col("at.row") == head.at[2])))
    return canonical(body.select((F.get("p", F.lit(0)).cast("long") - 1).alias("src"), (F.get("p", F.lit(1)).cast("long") - 1).alias("dst"), F.coalesce(F.get("p", F.lit(2)).cast("long"), F.lit(1)).alias("w")))


def write_coordinate(g: SplitGraph, path: str) -> None:
    """One text row an edge, ids from 1; rows before the first edge hold the header, in a file of their own that sorts first."""
    f = g.facts
    head = g.nodes.sparkSession.createDataFrame([(0, f"{f.n} {f.n} {f.m}")], "part int, value string")
    body = g.undirected().select(F.lit(1).alias("part"), F.concat_ws(" ", (F.col("src") + 1).cast("string"), (F.col("dst") + 1).cast("string"), F.col("w").cast("string")).alias("value"))
    head.unionByName(body).repartitionByRange(8, "part", "value").sortWithinPartitions("part", "value").select("value").write.text(path)


def write_adjacency(g: SplitGraph, path: str) -> None:
    """Adjacency text with both weights; needs ids 0 .. n - 1.  Lines are range-partitioned by id, so files read in order of name give the text."""
    f = g.facts
    lines = g.edges.groupBy("src").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("dst", "w"))), lambda x: F.concat_ws(" ", (x["dst"] + 1).cast("string"), x["w"].cast("string"))), " ").alias("line"))
    rows = g.nodes.join(lines, g.nodes["id"] == lines["src"], "left").select("id", F.concat_ws(" ", F.col("w").cast("string"), "line").alias("value"))
    head = g.nodes.sparkSession.createDataFrame([(-1, f"{f.n} {f.m} 11")], "id long, value string")
    head.unionByName(rows).repartitionByRange(8, "id").sortWithinPartitions("id").select("value").write.text(path)


def read_adjacency(spark: SparkSession, path: str) -> SplitGraph:
    """A graph from adjacency text; line numbers come from the sizes of the files' blocks, in order of name, not from one task."""
    lines = spark.read.text(path).where(~F.col("value").startswith("%")).select("value", F.monotonically_increasing_id().alias("at"), F.struct("_metadata.file_path", "_metadata.file_block_start").alias("part"))
    sizes = lines.groupBy("part").agg(F.count(F.lit(1)).alias("c"), F.min("at").alias("low")).withColumn("base", F.sum("c").over(W.orderBy("part")) - F.col("c")).select("part", "base", "low")
    numbered = lines.join(small(sizes), "part").select((F.col("base") + F.col("at") - F.col("low") - 1).alias("id"), F.split(F.trim("value"), r"\s+").alias("p"))
    fmt = numbered.where("id = -1").select(F.coalesce(F.get("p", F.lit(2)).cast("int"), F.lit(0))).first()[0]
    node_w, edge_w = fmt // 10 % 10, fmt % 10
    body = numbered.where("id >= 0")
    nodes = body.select("id", (F.get("p", F.lit(0)).cast("long") if node_w else F.lit(1).cast("long")).alias("w"))
    tokens = F.slice("p", 1 + node_w, F.greatest(F.size("p") - node_w, F.lit(0))) if node_w else F.filter("p", lambda x: x != "")
    flat = body.select(F.col("id").alias("src"), tokens.alias("t"))
    if edge_w:
        flat = flat.select("src", F.explode(F.transform(F.sequence(F.lit(0), F.expr("size(t) div 2 - 1")), lambda i: F.struct(F.get("t", i * 2).alias("dst"), F.get("t", i * 2 + 1).alias("w")))).alias("e")).where("e.dst is not null")
        pairs = flat.select("src", (F.col("e.dst").cast("long") - 1).alias("dst"), F.col("e.w").cast("long").alias("w"))
    else:
        pairs = flat.select("src", (F.explode("t").cast("long") - 1).alias("dst"), F.lit(1).cast("long").alias("w"))
    return from_edges(pairs.where("src < dst"), nodes=nodes, node_w="w")


def write_partition(part: DataFrame, path: str, by_block: bool = False) -> None:
    """(id, block) as Parquet; with ``by_block`` a folder for each block."""
    (part.write.partitionBy("block") if by_block else part.write).parquet(path)


def write_graph(g: SplitGraph, path: str) -> None:
    g.nodes.write.parquet(f"{path}/nodes")
    g.edges.sortWithinPartitions("src", "dst").write.parquet(f"{path}/edges")


def write_bucketed(g: SplitGraph, part: DataFrame, name: str, path: str, buckets: int = 64) -> tuple[DataFrame, DataFrame]:
    """Edges by source and blocks by id as two tables in equal buckets, ``name``_edges and ``name``_blocks, read back; their join needs no shuffle."""
    spark = g.nodes.sparkSession
    for kind, df, key in (("edges", g.edges, "src"), ("blocks", part, "id")):
        df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", f"{path}/{kind}").mode("overwrite").saveAsTable(f"{name}_{kind}")
    return spark.table(f"{name}_edges"), spark.table(f"{name}_blocks")


def read_graph(spark: SparkSession, path: str) -> SplitGraph:
    return SplitGraph(spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/edges"))


# ---------------------------------------------------------------- a data source for generated rings of cliques, read in parallel

class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class CliqueRingSource(DataSource):
    """``spark.read.format('clique_ring').option('cliques', b).option('size', s)``: b cliques of s nodes, each tied to the next by one edge."""

    @classmethod
    def name(cls) -> str:
        return "clique_ring"

    def schema(self) -> str:
        return "src long, dst long, w long"

    def reader(self, schema):
        return _CliqueRingReader(int(self.options.get("cliques", 8)), int(self.options.get("size", 10)), int(self.options.get("parts", 4)))


class _CliqueRingReader(DataSourceReader):
    def __init__(self, b: int, s: int, parts: int):
        self.b, self.s, self.parts = b, s, parts

    def partitions(self):
        return [_Range(self.b * i // self.parts, self.b * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, partition):
        for c in range(partition.low, partition.high):
            base = c * self.s
            for i in range(self.s):
                for j in range(i + 1, self.s):
                    yield base + i, base + j, 1
            if self.b > 1:
                yield base, (c + 1) % self.b * self.s, 1
