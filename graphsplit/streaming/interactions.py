"""Structured Streaming around a partition: windowed edge weights, deduplication, interval joins, placement of new nodes."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import mix
from ..storage import shared_folder, small, spill

#: Rounds in which new nodes without neighbours' room are dealt.
DEALS = 4


def event_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def tumbling(events: DataFrame, watermark: str = "1 hour", size: str = "1 hour") -> DataFrame:
    """(start, user_id, event_type, w): interactions of a user and a type in each window."""
    w = events.withWatermark("ts", watermark).groupBy(F.window("ts", size), "user_id", "event_type").agg(F.count(F.lit(1)).alias("w"))
    return w.select(F.col("window.start").alias("start"), "user_id", "event_type", "w")


def sliding(events: DataFrame, watermark: str = "1 hour", size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", watermark).groupBy(F.window("ts", size, step), "event_type").agg(F.count(F.lit(1)).alias("w"))
    return w.select(F.col("window.start").alias("start"), "event_type", "w")


def sessions(events: DataFrame, watermark: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, w): events of a user with no longer pause than the gap."""
    w = events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("w"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "w")


def without_repeats(events: DataFrame, keys: list[str], watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys)


def interval_join(views: DataFrame, buys: DataFrame, watermark: str = "1 hour", within: str = "interval 30 minutes") -> DataFrame:
    """(view_id, buy_id): a purchase after a view of the same user, within an interval."""
    v = views.select(F.col("event_id").alias("view_id"), F.col("user_id").alias("vu"), F.col("ts").alias("vt")).withWatermark("vt", watermark)
    b = buys.select(F.col("event_id").alias("buy_id"), F.col("user_id").alias("bu"), F.col("ts").alias("bt")).withWatermark("bt", watermark)
    return v.join(b, F.expr(f"vu = bu and bt >= vt and bt <= vt + {within}")).select("view_id", "buy_id")


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all files that are there now and return what it wrote."""
    return run_counted(stream, mode)[0]


def run_counted(stream: DataFrame, mode: str = "append") -> tuple[DataFrame, dict[str, int]]:
    """What the run wrote, and its counts: ``read``, the input rows, and ``dropped``, rows of partial states that came behind the watermark."""
    import uuid

    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/graphsplit/stream-{uuid.uuid4().hex}"
    query = stream.writeStream.format("parquet").outputMode(mode).option("path", f"{base}/rows").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    told = [json.loads(p.json) for p in query.recentProgress]
    counts = {"read": sum(p["numInputRows"] for p in told), "dropped": sum(s.get("numRowsDroppedByWatermark", 0) for p in told for s in p["stateOperators"])}
    return spark.read.schema(stream.schema).parquet(f"{base}/rows"), counts


def place_new_nodes(nodes: DataFrame, edges: DataFrame, part: DataFrame, caps: DataFrame, seed: int = 0) -> DataFrame:
    """(id, block) for new nodes (id, w): the block of most neighbour weight that has room, strict; else a block with room by hash.

    One superstep of refinement, for nodes that have no block yet; the rest is dealt by running weight into running room, and nodes
    that would pass their block's room try again in ``DEALS`` rounds with other orders.  A node that found no room has a null block.
    """
    from pyspark.sql import Window as W

    from ..operators.supersteps import admit, at_positions, running_weight

    held = caps.select("block", "cap", "held")
    room = small(held.select("block", (F.col("cap") - F.col("held")).alias("room")))
    near = edges.join(nodes.select(F.col("id").alias("dst")), "dst", "left_semi").join(part.select(F.col("id").alias("src"), "block"), "src").groupBy(F.col("dst").alias("id"), "block").agg(F.sum("w").alias("rate"))
    rated = near.join(room, "block").join(nodes, "id").where("w <= room")
    best = rated.groupBy("id", "w").agg(F.max_by(F.struct("block", "rate", "room"), F.struct("rate", mix("block", seed).alias("t"), "block")).alias("b"))
    placed = spill(admit(best.select("id", F.col("b.block").cast("long").alias("target"), F.col("b.rate").alias("gain"), "w", F.col("b.room").alias("room")), "strict", seed).select("id", F.col("target").cast("int").alias("block")), "placed")
    for r in range(DEALS):
        rest = spill(nodes.join(placed.select("id"), "id", "left_anti"), "rest")
        if not rest.take(1):
            return placed
        used = placed.join(nodes, "id").groupBy("block").agg(F.sum("w").alias("more"))
        line = held.join(used, "block", "left").select("block", F.floor(F.col("cap") - F.col("held") - F.coalesce("more", F.lit(0))).alias("room")).where("room >= 1")
        line = spill(line.withColumn("to", F.sum("room").over(W.orderBy(mix("block", seed + r), "block"))).withColumn("from", F.col("to") - F.col("room")), "line")
        length = line.agg(F.max("to")).first()[0]
        if length is None:
            break
        queue = running_weight(rest, seed=seed + r).withColumn("at", F.col("upto") - F.col("w"))
        more = at_positions(queue, line, float(length)).where(F.col("at") + F.col("w") <= F.col("to")).select("id", "block")
        placed = spill(placed.unionByName(more), "placed")
    return placed.unionByName(nodes.join(placed.select("id"), "id", "left_anti").select("id", F.lit(None).cast("int").alias("block")))
