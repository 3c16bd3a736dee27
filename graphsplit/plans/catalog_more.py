"""Queries for files, sinks, SQL functions and streams; registered into the catalogue."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sqlapi
from ..model import SplitGraph, from_edges
from ..operators import supersteps
from ..sources import files, synth, tables
from ..storage import shared_folder, spill, table
from ..streaming import interactions
from . import measures, partitioner
from .catalog import register, with_graph


def _place(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/graphsplit/{name}-{uuid.uuid4().hex}"


def roundtrip_edge_csv(spark: SparkSession, d: str) -> DataFrame:
    path = _place(spark, "csv")
    files.write_edge_csv(tables.user_next(spark, d), path)
    return files.read_edge_csv(spark, path)


def roundtrip_coordinate(spark: SparkSession, d: str) -> DataFrame:
    path = _place(spark, "coordinate")
    files.write_coordinate(from_edges(synth.grid(spark, 32, 32)), path)
    return files.read_coordinate(spark, path)


def roundtrip_adjacency(spark: SparkSession, d: str) -> DataFrame:
    path = _place(spark, "adjacency")
    files.write_adjacency(from_edges(synth.torus(spark, 16, 16), nodes=spark.range(256).withColumn("w", F.col("id") % 3 + 1), node_w="w"), path)
    return files.read_adjacency(spark, path).undirected()


register("roundtrip_edge_csv", roundtrip_edge_csv, tables.SQL["user_next"])
register("roundtrip_coordinate", roundtrip_coordinate, synth.SQL["grid"])
register("roundtrip_adjacency", roundtrip_adjacency, synth.SQL["torus"])


def sink_partition_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    path = _place(spark, "blocks")
    part = partitioner.mod_cut(table(spark, d, "part").select(F.col("p_partkey").alias("id")), 8)
    files.write_partition(part, path, by_block=True)
    return spark.read.schema("id long, block int").parquet(path).groupBy("block").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("low"))


register("sink_partition_roundtrip", sink_partition_roundtrip, "SELECT CAST(p_partkey % 8 AS INTEGER) AS block, count(*) AS n, min(p_partkey) AS low FROM part GROUP BY 1")


def source_clique_ring(spark: SparkSession, d: str) -> DataFrame:
    spark.dataSource.register(files.CliqueRingSource)
    return spark.read.format("clique_ring").option("cliques", 6).option("size", 5).load()


register("source_clique_ring", source_clique_ring, "SELECT a.i AS src, b.i AS dst, CAST(1 AS BIGINT) AS w FROM range(30) a(i), range(30) b(i) WHERE a.i < b.i AND a.i // 5 = b.i // 5 UNION ALL SELECT c * 5, (c + 1) % 6 * 5, 1 FROM range(6) t(c)")


def udf_formula_check(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    table(spark, d, "nation").createOrReplaceTempView("nation_rows")
    return spark.sql("SELECT n_nationkey AS i, round(limit_relaxed(1000, n_nationkey + 1, 0.03D, 7), 6) AS relaxed, round(eps_adaptive(0.03D, 800, 8, 404, 4), 9) AS eps, ceil2(n_nationkey) AS up, floor2(n_nationkey + 1) AS down, split_mix(n_nationkey) AS h FROM nation_rows")


from ..functions.hashing import mix_sql  # noqa: E402

register("udf_formula_check", udf_formula_check, f"SELECT n_nationkey AS i, round(greatest(1.03::DOUBLE * 1000 / (n_nationkey + 1), 1000.0::DOUBLE / (n_nationkey + 1) + 7), 6) AS relaxed, 0.009852455::DOUBLE AS eps, CAST(CASE WHEN n_nationkey <= 1 THEN 1 ELSE pow(2, ceil(log2(n_nationkey))) END AS BIGINT) AS up, CAST(pow(2, floor(log2(n_nationkey + 1))) AS BIGINT) AS down, CAST({mix_sql('n_nationkey::BIGINT', 0)} AS BIGINT) AS h FROM nation")


def udtf_neighbors(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    g = tables.load(spark, d, "nation_trade")
    g.edges.groupBy("src").agg(F.array_join(F.transform(F.collect_list(F.struct("dst", "w")), lambda x: F.concat_ws(":", x["dst"].cast("string"), x["w"].cast("string"))), ",").alias("adj")).createOrReplaceTempView("adjacency")
    return spark.sql("SELECT src, n.neighbor AS dst, n.w AS w FROM adjacency, LATERAL neighbors(adj) n")


register("udtf_neighbors", udtf_neighbors, with_graph("nation_trade", "SELECT src, dst, CAST(w AS BIGINT) AS w FROM d"))


def udtf_partition(spark: SparkSession, d: str) -> DataFrame:
    """(n, blocks, balanced): the table function on the nations' graph."""
    sqlapi.register(spark)
    tables.nation_trade(spark, d).createOrReplaceTempView("trade")
    return spark.sql("SELECT sum(n) AS n, count(*) AS blocks, max(n) <= 8 AS balanced FROM (SELECT block, count(*) AS n FROM partition_graph(TABLE(trade) WITH SINGLE PARTITION, 4) GROUP BY block)")


register("udtf_partition", udtf_partition, with_graph("nation_trade", "SELECT (SELECT count(*) FROM v) AS n, CAST(4 AS BIGINT) AS blocks, TRUE AS balanced"))


def estimator_blocks(spark: SparkSession, d: str) -> DataFrame:
    from ..operators.local import Options

    e = spill(tables.doc_lines(spark, d), "edges")
    g = from_edges(e)
    out = sqlapi.GraphSplitter(4, 0.05, Options(c=100, tries=1, repeats=1)).fit(e).transform(g.nodes)
    return out.agg(F.count_distinct("id").alias("n"), F.count_distinct("block").alias("blocks"))


register("estimator_blocks", estimator_blocks, with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS n, CAST(4 AS BIGINT) AS blocks"))


def place_partitions(spark: SparkSession, d: str) -> DataFrame:
    """(fewer): co-purchases that cross shards, shards by partition against shards by hash."""
    from ..operators.local import Options

    g = tables.load(spark, d, "doc_lines")
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    ours = measures.edge_cut(g, spill(partitioner.partition(g, 8, Options(c=100, tries=1, repeats=1)), "part")).withColumnRenamed("cut", "a")
    hashed = measures.edge_cut(g, partitioner.hash_cut(g.nodes, 8)).withColumnRenamed("cut", "b")
    return ours.crossJoin(hashed).select((F.col("a") < F.col("b")).alias("fewer"))


register("place_partitions", place_partitions, "SELECT TRUE AS fewer")

# ---------------------------------------------------------------- streams, run over what is there; the result is the batch query's


def _events(spark: SparkSession, d: str) -> DataFrame:
    """The events as a stream of files in order of time, so that nothing is late; a last row far ahead closes all windows."""
    path = _place(spark, "events")
    e = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    end = e.agg((F.max("ts") + F.expr("interval 4000 days")).alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), "ts", F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"))
    e.unionByName(end).repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
    return interactions.event_stream(spark, path, e.schema, 10)


def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return interactions.run_to_table(interactions.tumbling(_events(spark, d), "400 days")).where("user_id >= 0").withColumn("start", F.col("start").cast("timestamp_ntz"))


def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    return interactions.run_to_table(interactions.sliding(_events(spark, d), "400 days")).where("event_type <> 'end'").withColumn("start", F.col("start").cast("timestamp_ntz"))


def stream_session(spark: SparkSession, d: str) -> DataFrame:
    return interactions.run_to_table(interactions.sessions(_events(spark, d), "400 days")).where("user_id >= 0").withColumn("start", F.col("start").cast("timestamp_ntz"))


def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, n): one row for each user and type of those seen within the watermark."""
    out = interactions.run_to_table(interactions.without_repeats(_events(spark, d), ["user_id", "event_type"], "4000 days"))
    return out.where("user_id >= 0").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


def stream_interval_join(spark: SparkSession, d: str) -> DataFrame:
    e = _events(spark, d)
    return interactions.run_to_table(interactions.interval_join(e.where("event_type = 'view'"), _events(spark, d).where("event_type = 'purchase'"), "400 days"))


register("stream_tumbling", stream_tumbling, "SELECT date_trunc('hour', ts) AS start, user_id, event_type, count(*) AS w FROM events GROUP BY 1, 2, 3")
register("stream_sliding", stream_sliding, "SELECT s AS start, event_type, count(*) AS w FROM (SELECT date_trunc('hour', ts) - to_hours(i) AS s, event_type FROM events, range(2) t(i)) GROUP BY 1, 2")
register("stream_session", stream_session, """WITH m AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM m) SELECT user_id, min(ts) AS start, count(*) AS w FROM n GROUP BY user_id, s""")
register("stream_dedup", stream_dedup, "SELECT user_id, count(DISTINCT event_type) AS n FROM events GROUP BY 1")
register("stream_interval_join", stream_interval_join, "SELECT v.event_id AS view_id, b.event_id AS buy_id FROM events v JOIN events b ON v.user_id = b.user_id AND v.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= v.ts AND b.ts <= v.ts + INTERVAL 30 MINUTE")


def _late_stream(spark: SparkSession, d: str) -> DataFrame:
    """Events of which views come in the last file, behind the watermark.

    Lateness is judged by the watermark of the batch before, so a batch with one row stands between.
    """
    path = _place(spark, "late")
    e = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    end = e.agg((F.max("ts") + F.expr("interval 4000 days")).alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), "ts", F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"))
    e.where("event_type <> 'view'").unionByName(end).coalesce(1).write.parquet(path)
    end.write.mode("append").parquet(path)
    e.where("event_type = 'view'").coalesce(1).write.mode("append").parquet(path)
    return interactions.event_stream(spark, path, e.schema, 1)


def stream_late(spark: SparkSession, d: str) -> DataFrame:
    """(start, event_type, w): late views are dropped."""
    out = interactions.run_to_table(interactions.tumbling(_late_stream(spark, d)))
    return out.where("user_id >= 0").groupBy(F.col("start").cast("timestamp_ntz").alias("start"), "event_type").agg(F.sum("w").alias("w"))


register("stream_late", stream_late, "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS w FROM events WHERE event_type <> 'view' GROUP BY 1, 2")


def stream_placement(spark: SparkSession, d: str) -> DataFrame:
    """(placed, over): every third document is new and is placed on a partition of the others."""
    g = tables.load(spark, d, "doc_lines")
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    old = g.nodes.where("id % 3 <> 0")
    part = partitioner.mod_cut(old, 4)
    held = part.groupBy("block").agg(F.count(F.lit(1)).alias("held"))
    caps = held.select("block", "held", F.lit(1.05 * g.facts.weight / 4 + 1).alias("cap"))
    new = interactions.place_new_nodes(g.nodes.where("id % 3 = 0"), g.edges, part, caps)
    both = part.unionByName(new)
    over = both.groupBy("block").count().join(caps, "block").agg(F.count_if(F.col("count") > F.col("cap")).alias("over"))
    return both.agg(F.count_distinct("id").alias("placed")).crossJoin(over)


register("stream_placement", stream_placement, with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS placed, CAST(0 AS BIGINT) AS over"))


# ---------------------------------------------------------------- re-runs, co-grouped maps, observed counts, bucketed tables

def stream_late_counted(spark: SparkSession, d: str) -> DataFrame:
    """(late, noticed): input rows that reached no window, and whether the stream's own count of dropped rows tells of them."""
    stream, ends = _late_stream(spark, d), 2
    out, counts = interactions.run_counted(interactions.tumbling(stream))
    return out.where("user_id >= 0").agg((F.lit(counts["read"] - ends) - F.sum("w")).cast("long").alias("late")).withColumn("noticed", F.lit(counts["dropped"] > 0))


register("stream_late_counted", stream_late_counted, "SELECT count(*) AS late, TRUE AS noticed FROM events WHERE event_type = 'view'")


def rerun_matched(spark: SparkSession, d: str) -> DataFrame:
    """(plain, matched): nodes that change block from one partition to a later one with other names, before and after names are matched."""
    g = tables.load(spark, d, "user_next")
    g = SplitGraph(spill(g.nodes, "nodes"), g.edges)
    old = partitioner.mod_cut(g.nodes, 8)
    new = g.nodes.select("id", F.when(F.col("id") % 11 == 0, F.col("id") % 5).otherwise((F.col("id") + 3) % 8).cast("int").alias("block"))
    moved = lambda p: old.join(p.withColumnRenamed("block", "now"), "id").agg(F.count_if(F.col("block") != F.col("now")))
    return moved(new).toDF("plain").crossJoin(moved(measures.match_labels(g.nodes, old, new)).toDF("matched"))


register("rerun_matched", rerun_matched, with_graph("user_next", "SELECT count(*) FILTER (CASE WHEN id % 11 = 0 THEN id % 5 ELSE (id + 3) % 8 END <> id % 8) AS plain, count(*) FILTER (id % 11 = 0 AND (id % 5 + 5) % 8 <> id % 8) AS matched FROM v"))


def cogroup_inner(spark: SparkSession, d: str) -> DataFrame:
    g = tables.load(spark, d, "user_next")
    return measures.inner_weights(g, partitioner.mod_cut(g.nodes, 4))


register("cogroup_inner", cogroup_inner, with_graph("user_next", "SELECT CAST(b AS INTEGER) AS block, n, CAST(coalesce(i, 0) AS BIGINT) AS inner FROM (SELECT id % 4 AS b, count(*) AS n FROM v GROUP BY 1) LEFT JOIN (SELECT src % 4 AS b, sum(w) AS i FROM e WHERE src % 4 = dst % 4 GROUP BY 1) USING (b)"))


def observed_contraction(spark: SparkSession, d: str) -> DataFrame:
    """(rows, moved): counts observed while the parent map of a contraction is written."""
    g = tables.load(spark, d, "user_next")
    _, parent = supersteps.contract(g, g.nodes.select("id", "w", (F.col("id") % 40).alias("label")))
    return spark.createDataFrame([(parent._observed["rows"], parent._observed["moved"])], "rows long, moved long")


register("observed_contraction", observed_contraction, with_graph("user_next", "SELECT count(*) AS rows, count(*) - count(DISTINCT id % 40) AS moved FROM v"))


def bucketed_cut(spark: SparkSession, d: str) -> DataFrame:
    """(cut): by tables in buckets of the joined ids."""
    g = tables.load(spark, d, "user_next")
    edges, blocks = files.write_bucketed(g, partitioner.mod_cut(g.nodes, 4), f"graphsplit_{uuid.uuid4().hex}", _place(spark, "bucketed"), 8)
    return measures.edge_cut(SplitGraph(g.nodes, edges), blocks, "merge")


register("bucketed_cut", bucketed_cut, with_graph("user_next", "SELECT CAST(coalesce(sum(w), 0) AS BIGINT) AS cut FROM e WHERE src % 4 <> dst % 4"))
