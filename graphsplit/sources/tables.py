"""Graphs built from the given tables: undirected pairs (src, dst, w) with src < dst."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..model import SplitGraph, both_ways, canonical, from_edges
from ..storage import spill, table


def bipartite(df: DataFrame, left: str, right: str) -> DataFrame:
    """Pairs of a left and a right key, ids 2 * left and 2 * right + 1, weighed by rows."""
    ids = df.where(F.col(left).isNotNull() & F.col(right).isNotNull()).groupBy(left, right).agg(F.count(F.lit(1)).alias("w"))
    one, two = (F.col(left) * 2).cast("long"), (F.col(right) * 2 + 1).cast("long")
    # An even and an odd end name one pair of keys only, so no pair comes twice.
    return ids.select(F.least(one, two).alias("src"), F.greatest(one, two).alias("dst"), "w")


def cooccurrence(df: DataFrame, item: str, basket: str, most: int | None = None) -> DataFrame:
    """Pairs of items in one basket, weighed by the pairs of rows; baskets of more than ``most`` rows are left out as their pairs grow quadratically."""
    rows = df.select(F.col(item).alias("i"), F.col(basket).alias("b"))
    if most is not None:
        sizes = rows.groupBy("b").count().where(F.col("count").between(2, most)).select("b")
        rows = rows.join(sizes, "b")
    x, y = rows.select("b", F.col("i").alias("src")), rows.select("b", F.col("i").alias("dst"))
    return x.join(y, "b").where("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w")).select(F.col("src").cast("long"), F.col("dst").cast("long"), "w")


def successor(df: DataFrame, node: str, order: list[str], partition: list[str] | None = None, bucket=None) -> DataFrame:
    """Pairs of neighbours in an order.

    Without ``partition`` the order is global: ``bucket`` (a Column that rises with the order) cuts it into ranges; each is a window
    by itself, and the last row of a range is tied to the first of the next from a table with one row a range.
    """
    if partition:
        rows = df.withColumn("_next", F.lead(node).over(W.partitionBy(*partition).orderBy(*order)))
        return canonical(rows.where("_next is not null").select(F.col(node).alias("src"), F.col("_next").alias("dst"), F.lit(1).alias("w")))
    rows = df.withColumn("_range", bucket)
    inner = rows.withColumn("_next", F.lead(node).over(W.partitionBy("_range").orderBy(*order))).where("_next is not null").select(F.col(node).alias("src"), F.col("_next").alias("dst"))
    key = F.struct(*order)
    ends = rows.groupBy("_range").agg(F.min_by(node, key).alias("first"), F.max_by(node, key).alias("last"))
    seams = ends.withColumn("dst", F.lead("first").over(W.orderBy("_range"))).where("dst is not null").select(F.col("last").alias("src"), "dst")
    return canonical(inner.unionByName(seams).withColumn("w", F.lit(1)))


def cust_part(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    return bipartite(rows, "o_custkey", "l_partkey")


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    return cooccurrence(table(spark, d, "lineitem"), "l_partkey", "l_orderkey")


def supp_part(spark: SparkSession, d: str) -> DataFrame:
    return bipartite(table(spark, d, "lineitem"), "l_suppkey", "l_partkey")


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return bipartite(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def order_chain(spark: SparkSession, d: str) -> DataFrame:
    return successor(table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), "o_orderkey", ["o_orderdate", "o_orderkey"], ["o_custkey"])


def user_next(spark: SparkSession, d: str) -> DataFrame:
    return successor(table(spark, d, "events").select("user_id", "ts", "event_id"), "user_id", ["ts", "event_id"], bucket=F.date_trunc("day", "ts"))


def _lines(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= 20)


def _named_lines(spark: SparkSession, d: str) -> DataFrame:
    """(doc_id, line), written: distinct lines by their MD5, so that 16 bytes a line are shuffled, not its text, and texts are read once."""
    return spill(_lines(spark, d).select("doc_id", F.unhex(F.md5("line")).alias("line")).distinct(), "lines")


def doc_lines(spark: SparkSession, d: str) -> DataFrame:
    return cooccurrence(_named_lines(spark, d), "doc_id", "line", most=50)


def doc_lines_whole(spark: SparkSession, d: str, most: int = 50) -> DataFrame:
    """Documents 2 * id that share a line, in pairs; a line of more than ``most`` documents is a node of odd id, made of its MD5, tied to each of them."""
    lines = _named_lines(spark, d)
    often = lines.groupBy("line").count().where(F.col("count") > most).select("line")
    star = lines.join(often, "line").select((F.col("doc_id") * 2).alias("src"), (F.conv(F.substring(F.hex("line"), 1, 15), 16, 10).cast("long") * 2 + 1).alias("dst"), F.lit(1).cast("long").alias("w"))
    return canonical(cooccurrence(lines, "doc_id", "line", most).select((F.col("src") * 2).alias("src"), (F.col("dst") * 2).alias("dst"), "w").unionByName(star))


def nation_trade(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("src"))
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("dst"))
    return canonical(li.join(o, "l_orderkey").join(c, "o_custkey").join(s, "l_suppkey").select("src", "dst", F.lit(1).alias("w")))


def _numbered(pairs: DataFrame, left: str, right: str, most: int | None = 50) -> DataFrame:
    """Left ids and right texts in pairs; a text keeps its name.  Texts of one left id, or of more than ``most`` (None: no bound), are left out."""
    rows = pairs.groupBy(left, right).agg(F.count(F.lit(1)).alias("w"))
    counted = rows.groupBy(right).agg(F.count(left).alias("n")).where(F.col("n") >= 2 if most is None else F.col("n").between(2, most)).select(right)
    return rows.join(counted, right)


def page_links(spark: SparkSession, d: str, most: int | None = 50) -> DataFrame:
    words = table(spark, d, "pages").select(F.col("page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))).alias("word"))
    return _numbered(words, "src", "word", most).select("src", "word", "w")


def conv_words(spark: SparkSession, d: str, most: int | None = 50) -> DataFrame:
    words = table(spark, d, "conversations").select(F.col("conv_id").alias("src"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{3,})"), F.lit(1))).alias("word"))
    return _numbered(words, "src", "word", most).select("src", "word", "w")


def knn(df: DataFrame, key: str, vector: str, k: int = 10, blocks: int = 8) -> DataFrame:
    """The symmetric graph of the k nearest by cosine, weights round(1000 * (1 + cosine)); exact, block by block of queries.

    Each task holds one block of queries against a batch of rows; a partial top k a task keeps the shuffle at k rows a query and task.
    """
    import numpy as np
    import pyarrow as pa

    rows = df.where(F.col(vector).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int").alias("block"))
    queries = rows.select("block", "id", "v", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"), F.lit(0).alias("side"))
    sides = queries.unionByName(rows.select(F.col("block"), "id", "v", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"), F.lit(1).alias("side")).select(F.col("other").alias("block"), "id", "v", F.col("block").alias("other"), "side"))

    def near(table_: pa.Table) -> pa.Table:
        side, ids = table_.column("side").to_numpy(), table_.column("id").to_numpy()
        x = np.array(table_.column("v").to_pylist(), dtype=float)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        q, r = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        s = x[q] @ x[r].T
        s[ids[q][:, None] == ids[r][None, :]] = -np.inf
        top = np.argsort(-s, axis=1, kind="stable")[:, : k]
        out_q, out_r, sim = np.repeat(ids[q], top.shape[1]), ids[r][top].ravel(), np.take_along_axis(s, top, axis=1).ravel()
        ok = np.isfinite(sim)
        return pa.table({"a": out_q[ok], "b": out_r[ok], "sim": sim[ok]})

    best = sides.groupBy("block", "other").applyInArrow(near, "a long, b long, sim double")
    best = best.withColumn("rank", F.row_number().over(W.partitionBy("a").orderBy(F.desc(F.round("sim", 9)), "b"))).where(F.col("rank") <= k)
    pairs = best.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), F.round(1000 * (1 + F.col("sim"))).cast("long").alias("w"))
    return pairs.groupBy("src", "dst").agg(F.max("w").alias("w"))


def vec_knn(spark: SparkSession, d: str) -> DataFrame:
    return knn(table(spark, d, "embeddings"), "vec_id", "embedding")


#: Graphs with integer ids on both ends.
GRAPHS = {"cust_part": cust_part, "copurchase": copurchase, "supp_part": supp_part, "order_part": order_part, "order_chain": order_chain, "user_next": user_next, "doc_lines": doc_lines, "nation_trade": nation_trade}


def load(spark: SparkSession, d: str, name: str, node_w: str | None = None) -> SplitGraph:
    return from_edges(GRAPHS[name](spark, d), node_w=node_w)


def load_once(spark: SparkSession, d: str, name: str, node_w: str | None = None) -> SplitGraph:
    """The same as written tables; the edges are made from the input once, and nodes from the written edges.

    The graphs' pairs come once each with src < dst, so they are not summed again.
    """
    edges = spill(both_ways(GRAPHS[name](spark, d)), "edges")
    found = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    return SplitGraph(spill(found.select("id", (F.col("d") if node_w == "degree" else F.lit(1).cast("long")).alias("w")), "nodes"), edges)


_TWO_SIDED = "SELECT 2 * {l} AS src, 2 * {r} + 1 AS dst, count(*) AS w FROM {t} GROUP BY {l}, {r}"


def _ordered(sql: str) -> str:
    return f"SELECT CAST(least(src, dst) AS BIGINT) AS src, CAST(greatest(src, dst) AS BIGINT) AS dst, CAST(sum(w) AS BIGINT) AS w FROM ({sql}) WHERE src <> dst GROUP BY 1, 2"


#: The same graphs as SQL.
SQL = {
    "cust_part": _ordered(_TWO_SIDED.format(l="o_custkey", r="l_partkey", t="lineitem JOIN orders ON l_orderkey = o_orderkey")),
    "copurchase": _ordered("SELECT a.l_partkey AS src, b.l_partkey AS dst, 1 AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey"),
    "supp_part": _ordered(_TWO_SIDED.format(l="l_suppkey", r="l_partkey", t="lineitem")),
    "order_part": _ordered(_TWO_SIDED.format(l="l_orderkey", r="l_partkey", t="lineitem")),
    "order_chain": _ordered("SELECT * FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst, 1 AS w FROM orders) WHERE dst IS NOT NULL"),
    "user_next": _ordered("SELECT * FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst, 1 AS w FROM events) WHERE dst IS NOT NULL"),
    "doc_lines": """
        WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents) WHERE length(line) >= 20),
        k AS (SELECT line FROM l GROUP BY line HAVING count(*) BETWEEN 2 AND 50),
        m AS (SELECT doc_id, line FROM l JOIN k USING (line))
        SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS w FROM m a JOIN m b ON a.line = b.line AND a.doc_id < b.doc_id GROUP BY 1, 2""",
    "nation_trade": _ordered("SELECT c_nationkey AS src, s_nationkey AS dst, 1 AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
    "page_links": """
        WITH l AS (SELECT page_id AS src, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS word FROM pages),
        k AS (SELECT word FROM l GROUP BY word HAVING count(DISTINCT src) BETWEEN 2 AND 50)
        SELECT src, word, count(*) AS w FROM l JOIN k USING (word) GROUP BY src, word""",
    "conv_words": """
        WITH l AS (SELECT conv_id AS src, unnest(regexp_extract_all(lower(text), '([a-z]{3,})', 1)) AS word FROM conversations),
        k AS (SELECT word FROM l GROUP BY word HAVING count(DISTINCT src) BETWEEN 2 AND 50)
        SELECT src, word, count(*) AS w FROM l JOIN k USING (word) GROUP BY src, word""",
    "vec_knn": """
        WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
        s AS (SELECT a.vec_id AS a, b.vec_id AS b, list_cosine_similarity(a.e, b.e) AS sim FROM v a JOIN v b ON a.vec_id <> b.vec_id),
        t AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY round(sim, 9) DESC, b) AS r FROM s)
        SELECT least(a, b) AS src, greatest(a, b) AS dst, max(CAST(round(1000 * (1 + sim)) AS BIGINT)) AS w FROM t WHERE r <= 10 GROUP BY 1, 2""",
}

#: Without a bound on the owners of a line or word.
SQL |= {f"{name}_whole": SQL[name].replace("BETWEEN 2 AND 50", ">= 2") for name in ("page_links", "conv_words")}
SQL["doc_lines_whole"] = _ordered("""
        WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents) WHERE length(line) >= 20),
        c AS (SELECT line, count(*) AS n FROM l GROUP BY line), m AS (SELECT doc_id, line, n FROM l JOIN c USING (line))
        SELECT 2 * a.doc_id AS src, 2 * b.doc_id AS dst, 1 AS w FROM m a JOIN m b ON a.line = b.line AND a.doc_id < b.doc_id WHERE a.n <= 50
        UNION ALL SELECT 2 * doc_id, 2 * CAST('0x' || substr(md5(line), 1, 15) AS BIGINT) + 1, 1 FROM m WHERE n > 50""")
