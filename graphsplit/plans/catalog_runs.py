"""The experiment workloads as queries: real runs of our scheme and its rivals, their measures, and claims that SQL can state.

Measured tables (seconds, relative cuts) differ from machine to machine and have no SQL; ``*_claims`` hold what must come out on any.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import SplitGraph, from_edges
from ..operators import supersteps
from ..operators.local import Options
from ..sources import synth, tables
from ..storage import spill
from . import measures, partitioner, stats, workloads
from .catalog import register, with_graph

OURS = "one_cycle"
STRUCTURED = ("doc_lines", "user_next")
FAST = {"c": 100, "tries": 1, "repeats": 1}


def small_k_runs(spark: SparkSession, d: str) -> DataFrame:
    return workloads.run_small_k(spark, d, STRUCTURED, seeds=1, options=FAST)


def small_k(spark: SparkSession, d: str) -> DataFrame:
    """(algo, secs, relative_time, relative_cut, share_best, twice): small k, six schemes, seeds averaged first."""
    runs = small_k_runs(spark, d)
    means = stats.agg_seeds(runs)
    out = runs.groupBy("algo").agg(stats.geo_mean("secs").alias("secs"))
    for name, df in (("relative_time", stats.relative_time(runs, OURS)), ("relative_cut", stats.relative_cut(runs, OURS))):
        out = out.join(df.withColumnRenamed("relative", name), "algo")
    return out.join(stats.share_best(means).withColumnRenamed("share", "share_best"), "algo").join(stats.at_least_twice(means).withColumnRenamed("share", "twice"), "algo")


def feasible(runs: DataFrame) -> DataFrame:
    """(graph, k, feasible): every run ended and keeps the strict limit, which our graphs of unit weights allow."""
    return runs.groupBy("graph", "k").agg(F.bool_and((F.col("status") == "ok") & (F.col("max_block_w") <= F.col("strict_cap"))).alias("feasible"))


def ours(graph: str, ks: Callable[[int], list[int]], seeds: int = 1) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        n = tables.load(spark, d, graph).facts.n
        return feasible(workloads.run_grid(spark, d, [graph], ks(n), [OURS], seeds, options=FAST))

    return run


def all_feasible_sql(graph: str, ks: str) -> str:
    return with_graph(graph, f"WITH c AS (SELECT count(*) AS n FROM v) SELECT DISTINCT '{graph}' AS graph, CAST(k AS INTEGER) AS k, TRUE AS feasible FROM c, LATERAL (SELECT unnest({ks}) AS k)")


register("w1_small_k", small_k)
register("w1_small_k_feasible", ours("doc_lines", lambda n: list(workloads.SMALL_K), 2), all_feasible_sql("doc_lines", "[2, 4, 8, 16, 32, 64]"))


def large_k(spark: SparkSession, d: str) -> DataFrame:
    """(algo, timeouts, crashes, imbalanced, feasible, relative_time, relative_cut): many blocks of few nodes; rivals get ten times our longest run."""
    runs = workloads.run_large_k(spark, d, ("doc_lines",), seeds=1, options=FAST)
    out = stats.outcome_counts(runs).join(stats.relative_time(runs, OURS).withColumnRenamed("relative", "relative_time"), "algo", "left")
    return out.join(stats.relative_cut(runs, OURS).withColumnRenamed("relative", "relative_cut"), "algo", "left")


_LARGE_KS = "list_transform([128, 32, 8, 4], lambda x: greatest(2, CAST(pow(2, ceil(log2(greatest(n / x, 1)) - 1e-12)) AS INTEGER)))"
register("w2_large_k", large_k)
for _g in STRUCTURED:
    register(f"w2_feasible_{_g}", ours(_g, workloads.large_ks), all_feasible_sql(_g, _LARGE_KS))


def imbalance_of_failing(spark: SparkSession, d: str) -> DataFrame:
    """(algo, median, most): how far over the strict limit the rivals' infeasible runs are, for large k."""
    n = tables.load(spark, d, "doc_lines").facts.n
    return stats.imbalance_percentiles(workloads.run_grid(spark, d, ["doc_lines"], workloads.large_ks(n), ["direct_kway", "recursive_fixed"], options=FAST))


register("w2b_imbalance", imbalance_of_failing)
register("w4_predicted", lambda s, d: workloads.run_theory(s, d, ("doc_lines", "user_next"), options=FAST))
register("w5_ablation", workloads.run_ablation)


def theta_n(spark: SparkSession, d: str) -> DataFrame:
    """(k, ended, within): k in proportion to n; within is the relaxed limit, which holds for any weights, here of one each."""
    n = tables.load(spark, d, "doc_lines").facts.n
    runs = workloads.run_grid(spark, d, ["doc_lines"], [n // 4, n // 2], [OURS], options=FAST)
    relaxed = F.greatest((1 + F.col("eps")) * n / F.col("k"), F.lit(float(n)) / F.col("k") + 1)
    return runs.select("k", (F.col("status") == "ok").alias("ended"), (F.col("max_block_w") <= relaxed + 1e-6).alias("within"))


register("w6_theta_n", theta_n, with_graph("doc_lines", "WITH c AS (SELECT count(*) AS n FROM v) SELECT CAST(k AS INTEGER) AS k, TRUE AS ended, TRUE AS within FROM c, LATERAL (SELECT unnest([n // 4, n // 2]) AS k)"))

#: One rival of each kind of step; the others differ from these in one option.
WIDE = ("direct_kway", "recursive_adaptive", "single_level_lp")


def wide_rivals(spark: SparkSession, d: str) -> DataFrame:
    """(scheme, assigned, blocks_used, below_hash): rivals as frames, whose blocks and smallest graphs are split in tasks."""
    g = from_edges(synth.planted(spark))
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    o, out = Options(c=60, rounds=1, classes=1, tries=1, repeats=1), None
    hashed = measures.edge_cut(g, partitioner.hash_cut(g.nodes, 4)).first()[0]
    for scheme in WIDE:
        part = spill(partitioner.partition_wide(g, 4, scheme, o), "part")
        cut = measures.edge_cut(g, part).first()[0]
        one = part.agg(F.count_distinct("id").alias("assigned"), F.count_distinct("block").alias("blocks_used")).select(F.lit(scheme).alias("scheme"), "assigned", "blocks_used", F.lit(cut < hashed).alias("below_hash"))
        out = one if out is None else out.unionByName(one)
    return out


register("rivals_wide", wide_rivals, "SELECT scheme, CAST(400 AS BIGINT) AS assigned, CAST(4 AS BIGINT) AS blocks_used, TRUE AS below_hash FROM (VALUES " + ", ".join(f"('{s}')" for s in WIDE) + ") x(scheme)")


def lanes_wide(spark: SparkSession, d: str) -> DataFrame:
    """(lanes, assigned, blocks, over): the smallest graph's blocks from one copy, and from the best of four in tasks of their own."""
    g = from_edges(synth.planted(spark))
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    out = None
    for lanes in (1, 4):
        part, blocks = partitioner._bottom(g, 4, Options(c=40, tries=1, repeats=1, lanes=lanes), g.facts.weight, 4, partitioner.TASK_EDGES)
        caps = partitioner.caps_of(spark, blocks, g.facts.weight, 4, 0.03, g.facts.heaviest)
        over = supersteps.overload(g, part, caps).agg(F.count_if(F.col("over") > 0).alias("over"))
        one = part.agg(F.count_distinct("id").alias("assigned"), F.count_distinct("block").alias("blocks")).crossJoin(over).select(F.lit(lanes).alias("lanes"), "assigned", "blocks", "over")
        out = one if out is None else out.unionByName(one)
    return out


register("lanes_wide", lanes_wide, "SELECT CAST(l AS INTEGER) AS lanes, CAST(400 AS BIGINT) AS assigned, CAST(4 AS BIGINT) AS blocks, CAST(0 AS BIGINT) AS over FROM (VALUES (1), (4)) x(l)")
