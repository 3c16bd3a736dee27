"""The one-cycle partitioner and its rivals over frames.

``mode_for`` decides by size: graphs up to ``TASK_EDGES`` directed edges run whole in one grouped-map task (all instances of a batch side by
side), larger ones in supersteps until a level is small enough for a task.  Levels live in the shared folder.
"""

from __future__ import annotations

import json
import signal
import time
from dataclasses import asdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rules
from ..model import SplitGraph
from ..operators import local, supersteps
from ..operators.local import Options
from ..storage import small, spill, width

#: Directed edges of a graph that one task can take as rows, and packed (about 25 bytes an edge while a scheme runs).
TASK_EDGES, PACKED_EDGES = 2_000_000, 20_000_000
#: Rows that are packed together.
PACK = 1 << 18


def mode_for(m_directed: int, limit: int = TASK_EDGES) -> str:
    return "task" if m_directed <= limit else "distributed"


# ---------------------------------------------------------------- in one task, many instances at once

def rows_of(g: SplitGraph) -> DataFrame:
    """Nodes and edges in one frame: (kind, a, b, w)."""
    nodes = g.nodes.select(F.lit(0).alias("kind"), F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), "w")
    return nodes.unionByName(g.edges.select(F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), "w"))


def to_csr(table: pa.Table) -> tuple[np.ndarray, local.Csr]:
    """Node ids in ascending order, and the graph over their numbers."""
    kind, a, b, w = (table.column(c).to_numpy() for c in ("kind", "a", "b", "w"))
    nodes = kind == 0
    order = np.argsort(a[nodes])
    ids = a[nodes][order]
    e = kind == 1
    return ids, local.Csr(w[nodes][order], np.searchsorted(ids, a[e]), np.searchsorted(ids, b[e]), w[e])


def packed(g: SplitGraph) -> DataFrame:
    """Nodes and each edge once, as few rows of compressed arrays: (kind, many, a, b, w); sorted ids are kept as differences."""

    def pack(kind: int):
        def squeeze(x: np.ndarray) -> bytes:
            return pa.compress(np.ascontiguousarray(x, dtype=np.int64).tobytes(), codec="zstd", asbytes=True)

        def row(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
            a, b, w = (np.concatenate([x.column(i).to_numpy(zero_copy_only=False) for x in batches]) for i in range(3))
            order = np.lexsort((b, a))
            return pa.record_batch({"kind": pa.array([kind], pa.int32()), "many": pa.array([len(a)], pa.int64()), "a": [squeeze(np.diff(a[order], prepend=0))], "b": [squeeze(b[order])], "w": [squeeze(w[order])]})

        def run(batches):
            held, many = [], 0
            for x in batches:
                held, many = [*held, x], many + x.num_rows
                if many >= PACK:
                    yield row(held)
                    held, many = [], 0
            if many:
                yield row(held)

        return run

    schema = "kind int, many long, a binary, b binary, w binary"
    nodes = g.nodes.select(F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), F.col("w").cast("long").alias("w"))
    edges = g.undirected().select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").cast("long").alias("w"))
    return nodes.mapInArrow(pack(0), schema).unionByName(edges.mapInArrow(pack(1), schema))


def unpack(table: pa.Table) -> tuple[np.ndarray, local.Csr]:
    """Node ids in ascending order, and the graph over their numbers, from rows of ``packed``."""

    def spread(x, many: int) -> np.ndarray:
        return np.frombuffer(pa.decompress(x.as_buffer(), many * 8, codec="zstd"), dtype=np.int64)

    rows = list(zip(*(table.column(c) for c in ("kind", "many", "a", "b", "w")), strict=True))
    sizes = [r[1].as_py() for r in rows]
    nodes = [(np.cumsum(spread(a, n)), spread(w, n)) for (kind, _, a, _, w), n in zip(rows, sizes, strict=True) if kind.as_py() == 0]
    ids, nw = (np.concatenate(x) if x else np.zeros(0, dtype=np.int64) for x in (list(zip(*nodes, strict=True)) or [(), ()]))
    order = np.argsort(ids)
    ids, nw = ids[order], nw[order]
    ends, at = np.empty((2, sum(n for (kind, *_), n in zip(rows, sizes, strict=True) if kind.as_py() == 1)), dtype=np.int32), 0
    weights = []
    for (kind, _, a, b, w), n in zip(rows, sizes, strict=True):
        if kind.as_py() == 1:
            ends[0, at : at + n] = np.searchsorted(ids, np.cumsum(spread(a, n)))
            ends[1, at : at + n] = np.searchsorted(ids, spread(b, n))
            x, at = spread(w, n), at + n
            weights.append(x.astype(np.int32) if int(x.max()) < 1 << 31 else x)
    return ids, local.Csr.of_pairs(nw, ends[0], ends[1], np.concatenate(weights) if weights else np.zeros(0, dtype=np.int64))


def lanes_of(spark, count: int) -> DataFrame:
    """(inst, lane): lanes whose hashes lie in different shuffle partitions as long as there are any, so that instances do not queue in one task."""
    parts = width(spark)
    found = spark.range(40 * parts).select(F.col("id").cast("int").alias("lane")).select("lane", F.pmod(F.hash("lane"), F.lit(parts)).alias("p"))
    by = sorted(((r.p, r.lane) for r in found.collect()), key=lambda x: x[1])
    turns: dict[int, int] = {}
    order = []
    for p, lane in by:
        order.append((turns.get(p, 0), p, lane))
        turns[p] = turns.get(p, 0) + 1
    lanes = [lane for *_, lane in sorted(order)]
    return spark.createDataFrame([(i, lanes[i] if i < len(lanes) else i + 40 * parts) for i in range(count)], "inst int, lane int")


class TimeUp(Exception):
    """A run's time limit is over."""


def run_many(g: SplitGraph, instances: list[dict], limit: float | None = None, task_edges: int | None = PACKED_EDGES) -> DataFrame:
    """(inst, id, block, secs, status, phase): one row for each node and instance, and one of null id with the run's seconds, status and phases.

    An instance is a dict with scheme, k, and any of Options' fields; each is a group of its own, so instances run on as many cores
    as there are.  The graph goes to each of them packed.  A run that fails or that takes more than ``limit`` seconds has no rows of nodes.
    Graphs that no task can take raise ``ValueError``, unless ``task_edges`` is None.
    """
    if task_edges is not None and 2 * g.facts.m + g.facts.n > task_edges:
        raise ValueError(f"{2 * g.facts.m} directed edges are more than a task takes; use partition or partition_wide")
    spark = g.nodes.sparkSession
    rows = spill(packed(g), "packed").crossJoin(F.broadcast(lanes_of(spark, len(instances)))).repartition(width(spark), "lane")

    def stop(*_) -> None:
        raise TimeUp

    def run(group: pa.Table) -> pa.Table:
        inst = int(group.column("inst")[0].as_py())
        spec = dict(instances[inst])
        scheme, k = spec.pop("scheme", "one_cycle"), spec.pop("k")
        ids, csr = unpack(group)
        options, status, part = Options(**spec), "ok", None
        start = time.perf_counter()
        if limit:
            signal.signal(signal.SIGALRM, stop)
            signal.setitimer(signal.ITIMER_REAL, limit)
        try:
            part = local.SCHEMES[scheme](csr, min(k, max(csr.n, 1)), options)
        except TimeUp:
            status = "timeout"
        except Exception:
            if limit is None:
                raise
            status = "crash"
        finally:
            if limit:
                signal.setitimer(signal.ITIMER_REAL, 0)
        secs, n = time.perf_counter() - start, len(ids) if part is not None else 0
        phase = [("total", secs), *options.phases.items()]

        def after(first, rest: np.ndarray | None, kind: pa.DataType) -> pa.ChunkedArray:
            return pa.chunked_array([pa.array([first], kind), pa.nulls(n, kind) if rest is None else pa.array(rest[:n].astype(kind.to_pandas_dtype()))])

        return pa.table({
            "inst": pa.array(np.full(n + 1, inst, dtype=np.int32)), "id": after(None, ids, pa.int64()), "block": after(None, ids if part is None else part, pa.int32()),
            "secs": after(secs, None, pa.float64()), "status": after(status, None, pa.string()), "phase": after(phase, None, pa.map_(pa.string(), pa.float64())),
        })

    return rows.groupBy("lane", "inst").applyInArrow(run, "inst int, id long, block int, secs double, status string, phase map<string,double>")


def partition_many(g: SplitGraph, instances: list[dict]) -> DataFrame:
    """(inst, id, block): one row for each node and instance of ``run_many``, by the same steps for graphs of any size."""
    return run_many(g, instances, None, None).where("id is not null").select("inst", "id", "block")


# ---------------------------------------------------------------- supersteps

def large_blocks(g: SplitGraph, part: DataFrame, blocks: dict[int, int], task_edges: int) -> list[int]:
    """Blocks still to be split whose nodes and inner edges no task can take: at most one for each ``task_edges`` rows of the graph."""
    if 2 * g.facts.m + g.facts.n <= task_edges:
        return []
    sizes = part.groupBy("block").agg(F.count(F.lit(1)).alias("c")).unionByName(supersteps.induced(g, part).groupBy("block").agg(F.count(F.lit(1)).alias("c")))
    found = sizes.groupBy("block").agg(F.sum("c").alias("c")).where(F.col("c") > task_edges).select("block").collect()
    return sorted(r.block for r in found if blocks[r.block] > 1)


def halve_large(g: SplitGraph, part: DataFrame, halves: dict[int, tuple[int, int, int]], k: int, o: Options, total: int) -> DataFrame:
    """(id, block) of the blocks in ``halves`` (block: first new name and the two counts), all split at once as frames.

    Sides start by running weight inside each block; refinement sees inner edges only, so a node can only change to the other side.
    """
    spark = g.nodes.sparkSession
    table = spark.createDataFrame([(b, base, f0 / (f0 + f1)) for b, (base, f0, f1) in halves.items()], "block int, base int, share double")
    rows = spill(g.nodes.join(part, "id").join(small(table), "block"), "large")
    whole = rows.groupBy("block").agg(F.sum("w").alias("whole"))
    side = (F.col("upto") - F.col("w") >= F.col("share") * F.col("whole")).cast("int")
    start = spill(supersteps.running_weight(rows, ("block",), o.seed).join(small(whole), "block").select("id", (F.col("base") + side).alias("block")), "sides")
    own = SplitGraph(rows.select("id", "w"), spill(supersteps.induced(g, rows.select("id", "block")).select("src", "dst", "w"), "inner"))
    new = {base + i: f for base, f0, f1 in halves.values() for i, f in enumerate((f0, f1))}
    return supersteps.refine(own, start, caps_of(spark, new, total, k, o.eps, g.facts.heaviest), rounds=1, count=2, seed=o.seed)


def bisect_blocks(g: SplitGraph, part: DataFrame, blocks: dict[int, int], k: int, o: Options, total: int, stop: int | None = None, task_edges: int = TASK_EDGES) -> tuple[DataFrame, dict[int, int]]:
    """Split each block with a count above 1, each in its own task; with ``stop=1`` all remaining halvings at once.

    Blocks that no task can take are halved together as frames, again and again where ``stop=1``.
    Block names are dense after each step.  ``blocks`` has a row for each block, at most k.
    """
    large = set(large_blocks(g, part, blocks, task_edges))
    plan, nxt = {}, 0
    for b, f in sorted(blocks.items()):
        if f < 2:
            plan[b] = (nxt, [f])
        elif stop == 1 and b not in large:
            plan[b] = (nxt, [1] * f)
        else:
            plan[b] = (nxt, list(rules.split_count(f)))
        nxt += len(plan[b][1])
    halves = {b: (plan[b][0], *plan[b][1]) for b in large}
    here = part
    if large:
        named = small(g.nodes.sparkSession.createDataFrame([(b,) for b in large], "block int"))
        here = part.join(named, "block", "left_anti").select("id", "block")
    inner = supersteps.induced(g, here).select("block", F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), "w")
    rows = g.nodes.join(here, "id").select("block", F.lit(0).alias("kind"), F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), "w").unionByName(inner)

    def run(group: pa.Table) -> pa.Table:
        b = int(group.column("block")[0].as_py())
        ids, csr = to_csr(group)
        base, counts = plan[b]
        out = np.zeros(len(ids), dtype=np.int64)
        if len(counts) > 1:
            state = local.Blocks(np.array([blocks[b]]))
            step = 0
            while len(state.f) < len(counts):
                out, state = local.bisect_blocks(csr, out, state, k, o, total, o.seed + 31 * b + step)
                step += 1
        return pa.table({"id": pa.array(ids), "block": pa.array((base + out).astype(np.int32))})

    split = spill(rows.groupBy("block").applyInArrow(run, "id long, block int"), "split")
    after = {base + i: f for base, counts in plan.values() for i, f in enumerate(counts)}
    if large:
        parts = part.join(named, "block", "left_semi").select("id", "block")
        split = spill(split.unionByName(halve_large(g, parts, halves, k, o, total)), "split")
        if stop == 1 and any(f > 1 for f in after.values()):
            return bisect_blocks(g, split, after, k, o, total, stop, task_edges)
    return split, after


def caps_of(spark, blocks: dict[int, int], total: int, k: int, eps: float, heaviest: int) -> DataFrame:
    rows = [(b, float(rules.block_cap(total, k, eps, heaviest, f)), float(total * f / k)) for b, f in blocks.items()]
    return spark.createDataFrame(rows, "block int, cap double, share double")


def coarsen(g: SplitGraph, cap: float, o: Options, seed: int) -> tuple[SplitGraph, DataFrame]:
    found = supersteps.lp_cluster(g, cap, o.rounds, o.classes, o.order, o.enforce, o.active, seed)
    labels = supersteps.two_hop(found, g.facts.n, cap, g.edges, o.two_hop, seed) if o.two_hop != "off" else found.select("id", "w", "label")
    return supersteps.contract(g, spill(labels, "clusters"))


def _there(spark, path: str) -> bool:
    where = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)


def store_facts(g: SplitGraph, k: int, o: Options) -> str:
    """What names a hierarchy: the options, and the graph by its facts and by order-free hashes of its rows."""
    nodes = g.nodes.agg(F.bit_xor(F.xxhash64("id", "w"))).first()[0]
    edges = g.edges.agg(F.bit_xor(F.xxhash64("src", "dst", "w"))).first()[0]
    return json.dumps({"facts": asdict(g.facts), "nodes": nodes, "edges": edges, "k": k, "options": o.spec()}, sort_keys=True, default=str)


def claim_store(g: SplitGraph, store: str, k: int, o: Options) -> None:
    """Write the manifest of a new store; raise ``ValueError`` if the store holds another graph's or other options' levels."""
    spark, at, own = g.nodes.sparkSession, f"{store}/manifest", store_facts(g, k, o)
    if not _there(spark, at):
        spark.createDataFrame([(own,)], "value string").coalesce(1).write.mode("overwrite").text(at)
    elif (held := spark.read.text(at).first().value) != own:
        raise ValueError(f"{store} holds levels of {held}, not of {own}")


def kept_level(spark, store: str, depth: int) -> tuple[SplitGraph, DataFrame] | None:
    """A finished level of an earlier run: its coarse graph and parent map; the map is written last."""
    at = f"{store}/level-{depth}"
    if not _there(spark, f"{at}/parent"):
        return None
    return SplitGraph(spark.read.parquet(f"{at}/nodes"), spark.read.parquet(f"{at}/edges")), spark.read.parquet(f"{at}/parent")


def keep_level(store: str, depth: int, coarse: SplitGraph, parent: DataFrame) -> None:
    for name, df in (("nodes", coarse.nodes), ("edges", coarse.edges), ("parent", parent)):
        df.write.mode("overwrite").parquet(f"{store}/level-{depth}/{name}")


def descend(g: SplitGraph, k: int, o: Options, task_edges: int, store: str | None = None) -> tuple[list[tuple[SplitGraph, DataFrame]], SplitGraph]:
    levels, now, n0 = [], g, g.facts.n
    if store:
        claim_store(g, store, k, o)
    while now.facts.n > 2 * o.c and 2 * now.facts.m > task_edges:
        cap = max(rules.cluster_cap(o.eps, g.facts.weight, k, o.c, n0, now.facts.n), 1)
        found = kept_level(g.nodes.sparkSession, store, len(levels)) if store else None
        coarse, parent = found or coarsen(now, cap, o, o.seed + len(levels))
        if store and not found:
            keep_level(store, len(levels), coarse, parent)
        if coarse.facts.n > (1 - o.min_shrink) * now.facts.n:
            break
        levels.append((now, parent))
        now = coarse
    return levels, now


def _settle(g: SplitGraph, part: DataFrame, blocks: dict[int, int], k: int, o: Options, total: int, refine: bool = True) -> DataFrame:
    caps = caps_of(g.nodes.sparkSession, blocks, total, k, o.eps, g.facts.heaviest)
    part = supersteps.balance(g, part, caps, seed=o.seed)
    return supersteps.refine(g, part, caps, o.rounds, max(2, o.classes // 2), seed=o.seed, conflict=o.conflict == "independent") if refine else part


def partition(g: SplitGraph, k: int, o: Options | None = None, mode: str | None = None, task_edges: int = TASK_EDGES, store: str | None = None, check: bool = False) -> DataFrame:
    """(id, block): k blocks within the relaxed limit, by the one-cycle scheme.

    With ``store`` (a folder) the levels of the superstep path are kept there, and a later call goes on from the last finished one; a store
    of another graph, k or options is refused.  With ``check`` every level is tested: as many blocks as its size asks for, none above its limit.
    """
    o = o or Options(c=2000)
    facts = g.facts
    if k < 1 or k > max(facts.n, 1):
        raise ValueError("k must lie between 1 and the number of nodes")
    if k == 1 or facts.n == 0:
        return g.nodes.select("id", F.lit(0).alias("block"))
    mode = mode or mode_for(2 * facts.m, task_edges)
    if mode == "task":
        return run_many(g, [{"scheme": "one_cycle", "k": k, **o.spec()}], None, max(task_edges, TASK_EDGES)).where("id is not null").select("id", "block")
    with o.timed("coarsening"):
        levels, bottom = descend(g, k, o, task_edges, store)
    wanted = rules.level_blocks(bottom.facts.n, o.c, k, finest=not levels)
    # A bottom graph that fits a task gets its blocks from the same scheme there, with each block's final count.
    with o.timed("initial", bottom.facts.n):
        part, blocks = _bottom(bottom, k, o, facts.weight, wanted, task_edges)
    with o.timed("refinement", bottom.facts.n):
        part = _settle(bottom, part, blocks, k, o, facts.weight)
    if check:
        assure_level(bottom, part, blocks, k, o, facts.weight, wanted)
    for depth, (fine, parent) in reversed(list(enumerate(levels))):
        part = spill(supersteps.project(parent, part), "part")
        wanted = rules.level_blocks(fine.facts.n, o.c, k)
        with o.timed("initial", fine.facts.n):
            while len(blocks) < wanted and any(f > 1 for f in blocks.values()):
                part, blocks = bisect_blocks(fine, part, blocks, k, o, facts.weight, task_edges=task_edges)
        if depth > 0 or o.final_order == "twice" or len(blocks) == k:
            with o.timed("refinement", fine.facts.n):
                part = _settle(fine, part, blocks, k, o, facts.weight)
            if check:
                assure_level(fine, part, blocks, k, o, facts.weight, wanted)
    if len(blocks) < k:
        part, blocks = bisect_blocks(g, part, blocks, k, o, facts.weight, stop=1, task_edges=task_edges)
        part = _settle(g, part, blocks, k, o, facts.weight)
        if check:
            assure_level(g, part, blocks, k, o, facts.weight, k)
    return part


def assure_level(g: SplitGraph, part: DataFrame, blocks: dict[int, int], k: int, o: Options, total: int, wanted: int) -> None:
    """Raise ``AssertionError`` unless a level has the blocks that its size asks for and none of them is above its limit."""
    if len(blocks) < min(wanted, k):
        raise AssertionError(f"{len(blocks)} blocks where {wanted} are due")
    caps = caps_of(g.nodes.sparkSession, blocks, total, k, o.eps, g.facts.heaviest)
    heavy = supersteps.overload(g, part, caps).where("over > 1e-6").orderBy("block").first()
    if heavy is not None:
        raise AssertionError(f"block {heavy.block} weighs {heavy.held}, above {heavy.cap}")


def _bottom(g: SplitGraph, k: int, o: Options, total: int, wanted: int, task_edges: int) -> tuple[DataFrame, dict[int, int]]:
    if 2 * g.facts.m + g.facts.n > task_edges:  # coarsening came to a halt early, or C is large
        part, blocks = spill(g.nodes.select("id", F.lit(0).alias("block")), "part"), {0: k}
        while len(blocks) < wanted and any(f > 1 for f in blocks.values()):
            part, blocks = bisect_blocks(g, part, blocks, k, o, total, task_edges=task_edges)
        return part, blocks

    def run(group: pa.Table) -> pa.Table:
        lane = int(group.column("lane")[0].as_py())
        ids, csr = to_csr(group)
        own = Options(**{**spec, "lanes": 1, "seed": spec["seed"] if lanes == 1 else lanes * spec["seed"] + 1 + lane})
        part, blocks = _copy(csr, k, own, total, lanes) if csr.n > 1 else (np.zeros(csr.n, dtype=np.int64), local.Blocks(np.array([k])))
        while len(blocks.f) < wanted and (blocks.f > 1).any():
            part, blocks = local.bisect_blocks(csr, part, blocks, k, own, total, own.seed + len(blocks.f))
        over = int((csr.block_weights(part, len(blocks.f)) > blocks.caps(csr, k, own.eps)).sum())
        same = lambda x: pa.array([x] * len(ids), pa.int64())
        return pa.table({"lane": same(lane), "id": pa.array(ids), "block": pa.array(part.astype(np.int32)), "f": pa.array(blocks.f[part].astype(np.int32)), "over": same(over), "cut": same(csr.cut(part))})

    spec, lanes = o.spec(), max(1, o.lanes)
    # Each lane is a copy of the smallest graph in a task of its own; the best copy goes on.
    copies = rows_of(g).crossJoin(F.broadcast(g.nodes.sparkSession.range(lanes).withColumnRenamed("id", "lane")))
    found = spill(copies.groupBy("lane").applyInArrow(run, "lane long, id long, block int, f int, over long, cut long"), "bottom")
    best = found.select("over", "cut", "lane").distinct().orderBy("over", "cut", "lane").first()
    found = found.where(F.col("lane") == best.lane)
    blocks = {r.block: r.f for r in found.select("block", "f").distinct().collect()}
    return found.select("id", "block"), blocks


def _copy(g: local.Csr, k: int, o: Options, total: int, lanes: int) -> tuple[np.ndarray, local.Blocks]:
    """One lane: coarsen on from the common graph with the lane's own seed, once for each doubling of lanes, split, and come back."""
    levels = []
    now = g
    for depth in range((lanes - 1).bit_length()):
        coarse, parent = local.coarsen(now, max(rules.cluster_cap(o.eps, total, k, o.c, g.n, now.n), 1), o, o.seed + depth)
        if coarse.n < 2:
            break
        levels.append((now, parent))
        now = coarse
    part, blocks = local._bottom(now, k, o, total)
    for fine, parent in reversed(levels):
        part, blocks = local._level(fine, part[parent], blocks, rules.level_blocks(fine.n, o.c, k), k, o, total, o.seed)
    return part, blocks


# ---------------------------------------------------------------- rivals over frames

def descend_direct(g: SplitGraph, k: int, o: Options, how: str, least: int) -> tuple[list[tuple[SplitGraph, DataFrame]], SplitGraph]:
    """Levels down to ``least`` nodes, by label propagation or by heavy-edge matching with two-hop pairs."""
    levels, now, n0 = [], g, g.facts.n
    while now.facts.n > least:
        cap = max(rules.cluster_cap(o.eps, g.facts.weight, k, o.c, n0, now.facts.n), 1)
        if how == "match":
            cap = max(cap, 2.0 * now.facts.heaviest)
            labels = supersteps.match_two_hop(now, supersteps.match_heavy_edge(now, cap, 2, o.seed + len(levels)), cap, o.seed)
            coarse, parent = supersteps.contract(now, spill(labels, "clusters"))
        else:
            coarse, parent = coarsen(now, cap, o, o.seed + len(levels))
        if coarse.facts.n > (1 - o.min_shrink) * now.facts.n:
            break
        levels.append((now, parent))
        now = coarse
    return levels, now


def recursive_wide(g: SplitGraph, k: int, o: Options, task_edges: int = TASK_EDGES) -> DataFrame:
    """Every block split in two, again and again; blocks that a task can take are split there, the others as frames."""
    part, blocks = spill(g.nodes.select("id", F.lit(0).alias("block")), "part"), {0: k}
    while any(f > 1 for f in blocks.values()):
        part, blocks = bisect_blocks(g, part, blocks, k, o, g.facts.weight, task_edges=task_edges)
    return part


def direct_wide(g: SplitGraph, k: int, o: Options, how: str, search: int = 0, rebalance: bool = False, task_edges: int = TASK_EDGES) -> DataFrame:
    """Coarsen to k * C nodes, start there by recursive bisection, refine upwards; ``search`` more rounds of moves of best gain a level."""
    levels, now = descend_direct(g, k, o, how, min(max(k * o.c, 2 * k), max(g.facts.n - 1, 1)))
    part, one = recursive_wide(now, k, o, task_edges), {b: 1 for b in range(k)}
    for fine, parent in reversed(levels):
        part = spill(supersteps.project(parent, part), "part")
        heavy = fine.facts.heaviest if rebalance else 0
        caps = caps_of(g.nodes.sparkSession, one, g.facts.weight, k, o.eps, heavy)
        part = supersteps.refine(fine, part, caps, o.rounds + search, max(2, o.classes // 2), seed=o.seed)
        if rebalance:
            part = supersteps.balance(fine, part, caps, seed=o.seed)
    return part


def single_wide(g: SplitGraph, k: int, o: Options) -> DataFrame:
    """Blocks on the input graph only: dealt by running weight in hashed order, then repair and propagation in turn."""
    total = max(g.facts.weight, 1)
    start = supersteps.running_weight(g.nodes, seed=o.seed).select("id", F.least(F.lit(k - 1), F.floor((F.col("upto") - F.col("w")) * k / F.lit(total))).cast("int").alias("block"))
    caps = caps_of(g.nodes.sparkSession, {b: 1 for b in range(k)}, g.facts.weight, k, o.eps, g.facts.heaviest)
    return supersteps.refine(g, supersteps.balance(g, start, caps, seed=o.seed), caps, o.rounds, max(2, o.classes // 2), seed=o.seed)


def partition_wide(g: SplitGraph, k: int, scheme: str, o: Options, task_edges: int = TASK_EDGES) -> DataFrame:
    """(id, block) by any scheme as frames: no step gathers more than ``task_edges`` rows in a task."""
    if scheme == "one_cycle":
        return partition(g, k, o, "distributed", task_edges)
    if scheme in ("recursive_fixed", "recursive_adaptive"):
        return recursive_wide(g, k, Options(**{**o.spec(), "slack": scheme.removeprefix("recursive_")}), task_edges)
    if scheme == "single_level_lp":
        return single_wide(g, k, o)
    how = "match" if scheme in ("direct_kway", "local_matching") else "lp"
    return direct_wide(g, k, o, how, o.rounds if scheme == "kway_fm" else 0, scheme.startswith("local_"), task_edges)


def bisect_distributed(g: SplitGraph, f0: int, f1: int, eps: float, seed: int = 0) -> DataFrame:
    """(id, block) with two sides near f0 : f1 of a graph that no task can take: a start by running weight, repair, refinement."""
    share = f0 / (f0 + f1)
    total, heaviest = g.facts.weight, g.facts.heaviest
    start = supersteps.in_order(g.nodes, [F.col("id")]).select("id", (F.col("before") >= share * total).cast("int").alias("block"))
    rows = [(b, float(max((1 + eps) * total * s, total * s + heaviest)), float(total * s)) for b, s in ((0, share), (1, 1 - share))]
    caps = g.nodes.sparkSession.createDataFrame(rows, "block int, cap double, share double")
    return supersteps.refine(g, supersteps.balance(g, start, caps, seed=seed), caps, rounds=1, count=2, seed=seed)


def cost_log(g: SplitGraph, k: int, o: Options) -> DataFrame:
    """(level, n_before, m_before, n, m, moved): what each coarsening step of the superstep path did; moved counts nodes in a cluster not their own."""
    rows, now, n0 = [], g, g.facts.n
    while now.facts.n > 2 * o.c:
        cap = max(rules.cluster_cap(o.eps, g.facts.weight, k, o.c, n0, now.facts.n), 4)
        coarse, parent = coarsen(now, cap, o, o.seed + len(rows))
        moved = parent._observed["moved"]
        rows.append((len(rows) + 1, now.facts.n, now.facts.m, coarse.facts.n, coarse.facts.m, moved))
        if coarse.facts.n > (1 - o.min_shrink) * now.facts.n:
            break
        now = coarse
    return g.nodes.sparkSession.createDataFrame(rows, "level int, n_before long, m_before long, n long, m long, moved long")


# ---------------------------------------------------------------- trivial rivals

def mod_cut(nodes: DataFrame, k: int) -> DataFrame:
    return nodes.select("id", (F.col("id") % k).cast("int").alias("block"))


def hash_cut(nodes: DataFrame, k: int, seed: int = 0) -> DataFrame:
    from ..functions.hashing import mix

    return nodes.select("id", (mix("id", seed) % k).cast("int").alias("block"))


def weight_fill_cut(nodes: DataFrame, k: int) -> DataFrame:
    """Blocks by running weight in order of id."""
    total = nodes.agg(F.sum("w")).first()[0] or 1
    return supersteps.in_order(nodes, [F.col("id")]).select("id", F.least(F.lit(k - 1), F.expr(f"before * {k} div {total}")).cast("int").alias("block"))


def range_cut(nodes: DataFrame, k: int) -> DataFrame:
    """Blocks of equal numbers of nodes in order of id."""
    return weight_fill_cut(nodes.select("id", F.lit(1).cast("long").alias("w")), k)


def snake_cut(nodes: DataFrame, k: int) -> DataFrame:
    """Blocks dealt forth and back in order of falling weight, equal ones by id."""
    r = supersteps.in_order(nodes.withColumn("one", F.lit(1).cast("long")), [F.desc("w"), F.col("id")], "one").withColumnRenamed("before", "r")
    inside = F.col("r") % k
    return r.select("id", F.when(F.expr(f"r div {k}") % 2 == 0, inside).otherwise(k - 1 - inside).cast("int").alias("block"))
