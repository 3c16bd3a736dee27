"""The experiment workloads: each gives a frame of runs that ``stats`` reads.

A run is one scheme on one graph with one k and seed.  Seconds are measured around the job; cuts and weights come from certificates.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rules
from ..model import SplitGraph
from ..operators.local import Options
from ..sources import tables
from ..storage import spill
from . import measures, partitioner

RUNS = "algo string, graph string, k int, eps double, seed int, p int, secs double, cut long, max_block_w long, strict_cap double, status string, phase map<string,double>"
SMALL_K = (2, 4, 8, 16, 32, 64)


def time_run(spark: SparkSession, job, limit: float | None = None) -> tuple[str, float]:
    """('ok', 'timeout' or 'crash', seconds) of a callable that runs Spark jobs; a timer cancels its jobs by tag."""
    tag, start, fired = f"run-{uuid.uuid4().hex}", time.time(), []

    def stop() -> None:
        fired.append(1)
        spark.sparkContext.cancelJobsWithTag(tag)

    timer = threading.Timer(limit, stop) if limit else None
    spark.sparkContext.addJobTag(tag)
    if timer:
        timer.start()
    try:
        job()
        status = "ok"
    except Exception:
        status = "timeout" if fired else "crash"
    finally:
        if timer:
            timer.cancel()
        spark.sparkContext.removeJobTag(tag)
    return status, time.time() - start


def run_grid(spark: SparkSession, d: str, graphs: Iterable[str], ks: Iterable[int], schemes: Iterable[str], seeds: int = 1, eps: float = 0.03, limit: float | None = None, options: dict | None = None, p: int = 1, loaded: dict[str, SplitGraph] | None = None) -> DataFrame:
    """Runs of every scheme on every graph, k and seed: those of one graph side by side in one job, each timed in its own task.

    Graphs that the caller has are given by name in ``loaded``.
    """
    out = None
    for name in graphs:
        g = (loaded or {}).get(name) or tables.load_once(spark, d, name)
        specs = [{"scheme": s, "k": k, "seed": seed, "eps": eps, "cores": p, **(options or {})} for k in ks if k <= g.facts.n for s in schemes for seed in range(seeds)]
        found = spill(partitioner.run_many(g, specs, limit), "runs")
        cuts = measures.certify_many(g, found.where("id is not null").select("inst", "id", "block"), specs).select("inst", "cut", "max_block_w")
        table = spark.createDataFrame([(i, s["scheme"], name, s["k"], eps, s["seed"], p, float(rules.limit_strict(g.facts.weight, s["k"], eps))) for i, s in enumerate(specs)], "inst int, algo string, graph string, k int, eps double, seed int, p int, strict_cap double")
        runs = table.join(found.where("id is null").select("inst", "secs", "status", "phase"), "inst").join(cuts, "inst", "left")
        runs = runs.select("algo", "graph", "k", "eps", "seed", "p", "secs", F.col("cut").cast("long").alias("cut"), F.col("max_block_w").cast("long").alias("max_block_w"), "strict_cap", "status", "phase")
        out = runs if out is None else out.unionByName(runs)
    return spill(out, "grid")


def run_small_k(spark: SparkSession, d: str, graphs=("doc_lines", "user_next", "copurchase"), schemes=("one_cycle", "direct_kway", "kway_fm", "single_level_lp", "local_matching", "local_lp"), seeds: int = 5, options: dict | None = None) -> DataFrame:
    return run_grid(spark, d, graphs, SMALL_K, schemes, seeds, options=options or {"c": 200})


def run_large_k(spark: SparkSession, d: str, graphs=("doc_lines", "user_next"), schemes=("one_cycle", "direct_kway", "recursive_fixed", "kway_fm", "single_level_lp"), seeds: int = 3, options: dict | None = None) -> DataFrame:
    """k the powers of two nearest n / 128, n / 32, n / 8 and n / 4; the limit is ten times our longest run."""
    out = None
    for name in graphs:
        g = tables.load_once(spark, d, name)
        ks, own = large_ks(g.facts.n), {"options": options or {"c": 100}, "loaded": {name: g}}
        ours = run_grid(spark, d, [name], ks, ["one_cycle"], seeds, **own)
        limit = 10 * ours.agg(F.max("secs")).first()[0]
        rest = run_grid(spark, d, [name], ks, [s for s in schemes if s != "one_cycle"], seeds, limit=limit, **own)
        both = ours.unionByName(rest)
        out = both if out is None else out.unionByName(both)
    return out


def run_theta_n(spark: SparkSession, d: str, name: str = "doc_lines") -> DataFrame:
    """k in proportion to n: n / 2 and n / 4."""
    n = tables.load(spark, d, name).facts.n
    return run_grid(spark, d, [name], [n // 4, n // 2], ["one_cycle"], options={"c": 100})


def run_ablation(spark: SparkSession, d: str, name: str = "doc_lines", k: int = 8) -> DataFrame:
    """(variant, cut, max_block_w, over_relaxed): each option changed alone."""
    variants = [("default", {})] + [(f"{o}={v}", {o: v}) for o, vs in {"two_hop": ("off", "groups"), "active": (False,), "order": ("degree", "random", "id"), "enforce": ("soft", "sampled"), "final_order": ("once",), "pool": (("random",), ("bfs",), ("grow",)), "slack": ("fixed",), "conflict": ("none",), "lanes": (2, 4)}.items() for v in vs]
    specs = [{"k": k, "c": 60, **v} for _, v in variants]
    g = tables.load(spark, d, name)
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    found = measures.certify_many(g, spill(partitioner.partition_many(g, specs), "parts"), [{**s, "name": n} for s, (n, _) in zip(specs, variants, strict=True)])
    return found.select(F.col("scheme").alias("variant"), "cut", "max_block_w", "over_relaxed")


def run_theory(spark: SparkSession, d: str, graphs=("user_next", "doc_lines", "copurchase"), ks=(4, 16, 64), p: int = 4, c: int = 200, options: dict | None = None) -> DataFrame:
    """(graph, k, n, predicted, secs): idealised cost beside measured seconds."""
    runs = run_grid(spark, d, graphs, ks, ["one_cycle"], options={"c": c, **(options or {})}, p=p)
    sizes = {name: tables.load(spark, d, name).facts.n for name in graphs}
    table = spark.createDataFrame([(g, k, n, rules.predicted_cost(n, p, k, (options or {}).get("c", c))) for g, n in sizes.items() for k in ks], "graph string, k int, n long, predicted double")
    return runs.select("graph", "k", "secs").join(F.broadcast(table), ["graph", "k"])


def run_scaling(spark: SparkSession, d: str, name: str = "user_next", k: int = 8, ps: Iterable[int] = (1, 2, 4), c: int = 20, task_edges: int = 4000) -> DataFrame:
    """Runs of the superstep path with p shuffle partitions, so that at most p tasks of a step run at once; phases by the 2 p C rule."""
    rows, before = [], spark.conf.get("spark.sql.shuffle.partitions")
    g = tables.load(spark, d, name)
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    try:
        for p in ps:
            spark.conf.set("spark.sql.shuffle.partitions", str(p))
            own = SplitGraph(spill(g.nodes.repartition(p, "id"), "nodes"), spill(g.edges.repartition(p, "src"), "edges"))
            o, start = Options(c=c, rounds=1, classes=1, tries=1, repeats=1, cores=p), time.time()
            part = spill(partitioner.partition(own, k, o, "distributed", task_edges), "part")
            secs, cut = time.time() - start, measures.edge_cut(own, part).first()[0]
            top = measures.block_weights(own, part).agg(F.max("w")).first()[0]
            rows.append(("one_cycle", name, k, o.eps, 0, p, secs, cut, top, float(rules.limit_strict(own.facts.weight, k, o.eps)), "ok", dict(o.phases)))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return spark.createDataFrame(rows, RUNS)


def large_ks(n: int) -> list[int]:
    """The powers of two next to n / 128, n / 32, n / 8 and n / 4."""
    return sorted({max(2, rules.ceil2(n / x)) for x in (128, 32, 8, 4)})
