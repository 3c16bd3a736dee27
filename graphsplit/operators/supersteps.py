"""The methods' steps as DataFrame plans: ratings, admission, clustering, two-hop, contraction, projection, balance, refinement.

A superstep reads the labels of its start, so its result depends on nothing but them, hashes and ids.  A label frame is
(id, w, label).  Sums by (node, label) have map-side partial sums, so a hub's edges are never one task's; what is ordered by a window
is proposals only, and a large target's are thinned to its marginal gain bin first.  Frames between rounds are written to the
shared folder.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, mix
from ..model import SplitGraph
from ..storage import release, small, spill, width

BINS = 64
#: Slices of ids that running sums go through, and bins of a hash that a quota is cut from.
SLICES = 1024
#: Nodes of one favourite that one window pairs up.
PAIRED_AT_ONCE = 4096
#: The favourite of nodes without edges; no id is that small.
NO_NEIGHBOUR = -(1 << 63)


def running_weight(rows: DataFrame, by: tuple[str, ...] = (), seed: int = 0, slices: int = SLICES) -> DataFrame:
    """``rows`` (id, w, ...) with upto: the weight up to and with each row of its ``by``, slice of hashed ids by slice.

    Slices are summed first, so no window holds more than one slice of one group.
    """
    cut = rows.withColumn("_s", mix("id", seed) % slices)
    sums = cut.groupBy(*by, "_s").agg(F.sum("w").alias("_sw"))
    bases = sums.withColumn("_base", F.sum("_sw").over(W.partitionBy(*by).orderBy("_s")) - F.col("_sw")).drop("_sw")
    inside = W.partitionBy(*by, "_s").orderBy("id").rowsBetween(W.unboundedPreceding, 0)
    return cut.join(small(bases), [*by, "_s"]).withColumn("upto", F.col("_base") + F.sum("w").over(inside)).drop("_s", "_base")


def in_order(rows: DataFrame, order: list[Column], w: str = "w") -> DataFrame:
    """``rows`` with before: the weight of all rows that come earlier in ``order``, which must tell rows apart.

    Rows are dealt to ranges of the whole order, so equal values of its first columns are no hot key; a window holds one range.
    """
    cut = spill(rows.repartitionByRange(width(rows.sparkSession), *order).withColumn("_p", F.spark_partition_id()), "ranges")
    sums = cut.groupBy("_p").agg(F.sum(w).alias("_s"))
    bases = sums.select("_p", (F.sum("_s").over(W.orderBy("_p")) - F.col("_s")).alias("_base"))
    inside = W.partitionBy("_p").orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    return cut.join(small(bases), "_p").withColumn("before", F.col("_base") + F.sum(w).over(inside) - F.col(w)).drop("_p", "_base")


def at_positions(rows: DataFrame, spans: DataFrame, length: float) -> DataFrame:
    """``rows`` (at, ...) joined with the span (from, to, ...) that holds their position; an equi-join on cells of the line of ``length``."""
    cell = max(length / SLICES, 1e-9)
    cells = spans.withColumn("_cell", F.explode(F.sequence(F.floor(F.col("from") / cell), F.floor(F.col("to") / cell))))
    placed = rows.withColumn("_cell", F.floor(F.col("at") / cell))
    return placed.join(small(cells), "_cell").where((F.col("at") >= F.col("from")) & (F.col("at") < F.col("to"))).drop("_cell")


def first_by_hash(rows: DataFrame, key: str, quota: int, seed: int) -> DataFrame:
    """The ``quota`` rows of least (hash of ``key``, id); only the bin of hashes in which the quota ends is ordered."""
    width = PRIME // SLICES + 1
    binned = rows.withColumn("_h", mix(key, seed)).withColumn("_bin", F.expr(f"_h div {width}"))
    left, last = quota, None
    for r in sorted(binned.groupBy("_bin").agg(F.count(F.lit(1)).alias("c")).collect(), key=lambda r: r._bin):
        if left < r.c:
            last = r._bin
            break
        left -= r.c
    if last is None:
        return rows
    ranked = binned.where(F.col("_bin") == last).withColumn("_r", F.row_number().over(W.partitionBy("_bin").orderBy("_h", "id"))).where(F.col("_r") <= left)
    return binned.where(F.col("_bin") < last).drop("_h", "_bin").unionByName(ranked.drop("_h", "_bin", "_r"))


# ---------------------------------------------------------------- ratings and admission

def messages(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(id, label, w): each edge as what its source tells its target."""
    return edges.join(labels.select(F.col("id").alias("src"), "label"), "src").select(F.col("dst").alias("id"), "label", "w")


def ratings(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(id, label, rate): edge weight from each node to each label next to it."""
    return messages(edges, labels).groupBy("id", "label").agg(F.sum("w").alias("rate"))


def label_weights(labels: DataFrame) -> DataFrame:
    return labels.groupBy("label").agg(F.sum("w").alias("held"))


def active_nodes(edges: DataFrame, moved: DataFrame) -> DataFrame:
    """Nodes with a neighbour among ``moved`` (id)."""
    return edges.join(moved.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()


def classes(nodes: DataFrame, edges: DataFrame, order: str, count: int, seed: int) -> DataFrame:
    """(id, cls): the sub-round in which a node acts."""
    if order == "id" or count == 1:
        return nodes.select("id", F.lit(0).alias("cls"))
    if order == "random":
        return nodes.select("id", (mix("id", seed) % count).cast("int").alias("cls"))
    degree = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    both = nodes.join(degree, "id", "left").select("id", F.coalesce("d", F.lit(0)).alias("d"))
    bucket = F.when(F.col("d") > 0, F.length(F.bin("d")) - 1).otherwise(F.lit(-1))
    # Classes follow the buckets' sizes; the table of buckets has at most 64 rows.
    sizes = both.groupBy(bucket.alias("b")).agg(F.count(F.lit(1)).alias("size"))
    below = sizes.withColumn("below", F.sum("size").over(W.orderBy("b")) - F.col("size")).withColumn("all", F.sum("size").over(W.partitionBy()))
    fraction = mix(F.expr("id div 64") if order == "bucket" else F.col("d"), seed) / F.lit(float(PRIME))
    placed = both.withColumn("b", bucket).join(F.broadcast(below), "b")
    return placed.select("id", F.least(F.lit(count - 1), F.floor((F.col("below") + F.col("size") * fraction) * count / F.col("all"))).cast("int").alias("cls"))


def running(proposals: DataFrame) -> DataFrame:
    """``proposals`` (id, target, gain, w, room) with run: weight asked of the target up to and with each, best gain first."""
    # A bin of gain is wholly in, wholly out, or the marginal one; only the marginal one needs an order.
    peak = proposals.groupBy("target").agg(F.max("gain").alias("top"), F.sum("w").alias("asked"))
    binned = proposals.join(peak, "target").withColumn("bin", F.least(F.lit(BINS - 1), F.floor((F.col("top") - F.col("gain")) * F.lit(BINS) / F.greatest(F.abs("top"), F.lit(1)))).cast("int"))
    sums = binned.groupBy("target", "bin").agg(F.sum("w").alias("binw"))
    sums = sums.withColumn("upto", F.sum("binw").over(W.partitionBy("target").orderBy("bin")))
    both = binned.join(sums, ["target", "bin"])
    inside = W.partitionBy("target", "bin").orderBy(F.desc("gain"), "tie", "id").rowsBetween(W.unboundedPreceding, 0)
    sure = both.where((F.col("upto") <= F.col("room")) & (F.col("asked") >= 0)).withColumn("run", F.col("upto"))
    marginal = both.where((F.col("upto") > F.col("room")) & (F.col("upto") - F.col("binw") < F.col("room"))).withColumn("run", F.col("upto") - F.col("binw") + F.sum("w").over(inside))
    return sure.unionByName(marginal).drop("top", "asked", "bin", "binw", "upto")


def admit(proposals: DataFrame, how: str, seed: int) -> DataFrame:
    """Granted rows of ``proposals`` (id, target, gain, w, room): soft grants all, strict what fits in order of gain, sampled a share drawn by hash."""
    if how == "soft":
        return proposals
    if how == "sampled":
        demand = proposals.groupBy("target").agg(F.sum("w").alias("demand"))
        return proposals.join(demand, "target").where(mix("id", seed) / F.lit(float(PRIME)) < F.col("room") / F.col("demand")).drop("demand")
    return running(proposals.withColumn("tie", mix("id", seed))).where("run <= room").drop("run", "tie")


def _best(by: str, *order: Column) -> Column:
    return F.max_by(F.struct(by), F.struct(*order))


# ---------------------------------------------------------------- clustering

def propose(edges: DataFrame, labels: DataFrame, cap: float, seed: int) -> DataFrame:
    """(id, w, label, target, gain, room, fav): each node's best label with room, and its best label if size keeps it out."""
    rated = ratings(edges, labels)
    held = label_weights(labels)
    own = labels.select("id", "w", F.col("label").alias("mine"))
    rows = rated.join(held, "label").join(own, "id")
    fits = (F.col("label") == F.col("mine")) | (F.col("held") + F.col("w") <= cap)
    tie = mix("label", seed)
    rows = rows.select("id", "w", "mine", "label", "rate", "held", fits.alias("fits"), tie.alias("tie"))
    key = F.struct("rate", "tie", "label")
    pick = F.struct("label", "rate", "held", "tie")
    best = rows.groupBy("id", "w", "mine").agg(
        F.max_by(pick, F.when(F.col("fits"), key)).alias("best"), F.max_by(F.struct("label", "fits"), key).alias("top"), F.coalesce(F.max(F.when(F.col("label") == F.col("mine"), F.col("rate"))), F.lit(0)).alias("stay"),
    )
    return best.select(
        "id", "w", F.col("mine").alias("label"), F.col("best.label").alias("target"), (F.col("best.rate") - F.col("stay")).alias("gain"),
        (F.lit(cap) - F.col("best.held")).alias("room"), F.when(~F.col("top.fits"), F.col("top.label")).alias("fav"), F.col("best.tie").alias("target_tie"),
    )


def lp_cluster(g: SplitGraph, cap: float, rounds: int = 5, count: int = 4, order: str = "bucket", enforce: str = "strict", active: bool = True, seed: int = 0) -> DataFrame:
    """(id, w, label, fav): size-constrained label propagation from single nodes."""
    labels = spill(g.nodes.select("id", "w", F.col("id").alias("label"), F.lit(None).cast("long").alias("fav")).join(classes(g.nodes, g.edges, order, count, seed), "id"), "labels")
    moved_before = None
    for r in range(rounds):
        moved_ids, any_moved = [], False
        may = None if moved_before is None or not active else spill(active_nodes(g.edges, moved_before), "active")
        for c in range(count if order != "id" else 1):
            acting = labels.where(F.col("cls") == c).select("id")
            if may is not None:
                acting = acting.join(may, "id", "left_semi")
            own = g.edges.join(acting.withColumnRenamed("id", "dst"), "dst", "left_semi")
            asked = spill(propose(own, labels.select("id", "w", "label"), cap, seed + r), "asked")
            wish = asked.where((F.col("target") != F.col("label")) & ((F.col("gain") > 0) | ((F.col("gain") == 0) & (F.col("target_tie") > mix("label", seed + r)))))
            moves = spill(admit(wish.select("id", "target", "gain", "w", "room"), enforce, seed + r).select("id", "target"), "moves")
            favs = asked.select("id", F.coalesce("fav", F.when(F.col("target") != F.col("label"), F.col("target"))).alias("newfav"))
            after = labels.join(moves, "id", "left").join(favs, "id", "left").select("id", "w", F.coalesce("target", "label").alias("label"), F.coalesce("newfav", "fav").alias("fav"), "cls")
            after = spill(after, "labels")
            release(labels, asked)
            labels = after
            moved_ids.append(moves.select("id"))
            any_moved = any_moved or bool(moves.take(1))
        if not any_moved:
            break
        moved_before = moved_ids[0]
        for m in moved_ids[1:]:
            moved_before = moved_before.unionByName(m)
    return labels.drop("cls")


def two_hop(clustering: DataFrame, n: int, cap: float, edges: DataFrame | None = None, mode: str = "pairs", seed: int = 0) -> DataFrame:
    """(id, w, label): clusters of one node with one favourite merged until half the nodes are left.

    With ``edges``, nodes that have none share a favourite of their own, so that they shrink too.
    """
    sizes = clustering.groupBy("label").agg(F.count(F.lit(1)).alias("size"))
    quota = sizes.count() - n // 2
    plain = clustering.select("id", "w", "label")
    if quota <= 0:
        return plain
    lookup = clustering.select(F.col("id").alias("fav"), F.col("label").alias("fav_now"))
    single = clustering.join(sizes.where("size = 1"), "label")
    lone = single.where("fav is not null").join(lookup, "fav", "left").select("id", "w", "label", F.coalesce("fav_now", "fav").alias("fav"))
    if edges is not None:
        apart = single.where("fav is null").join(edges.select(F.col("src").alias("id")), "id", "left_anti")
        lone = lone.unionByName(apart.select("id", "w", "label", F.lit(NO_NEIGHBOUR).alias("fav")))
    # A hub may be the favourite of a third of all nodes: its nodes are paired in parts.
    lone = spill(lone, "lone")
    parts = lone.groupBy("fav").agg((F.count(F.lit(1)) / F.lit(PAIRED_AT_ONCE)).cast("long").alias("parts")).where("parts > 0")
    lone = lone.join(small(parts), "fav", "left").withColumn("part", F.when(F.col("parts").isNull(), 0).otherwise(mix("id", seed + 7) % (F.col("parts") + 1))).drop("parts")
    by = W.partitionBy("fav", "part").orderBy("w", mix("id", seed), "id")
    if mode == "groups":
        bin_ = F.floor((F.sum("w").over(by.rowsBetween(W.unboundedPreceding, 0)) - 1) / F.lit(max(int(cap), 1)))
        grouped = lone.withColumn("bin", bin_).withColumn("head", F.first("label").over(W.partitionBy("fav", "part", "bin").orderBy("w", "id")))
        joins = grouped.where("head <> label").select("id", F.col("head").alias("into"))
    else:
        ranked = lone.withColumn("r", F.row_number().over(by))
        pair = W.partitionBy("fav", "part", F.expr("(r - 1) div 2")).orderBy("r")
        paired = ranked.withColumn("into", F.lag("label").over(pair)).withColumn("other", F.lag("w").over(pair))
        joins = paired.where((F.col("into").isNotNull()) & (F.col("w") + F.col("other") <= cap)).select("id", "into")
    chosen = first_by_hash(spill(joins, "joins"), "into", quota, seed + 1)
    return plain.join(chosen, "id", "left").select("id", "w", F.coalesce("into", "label").alias("label"))


# ---------------------------------------------------------------- contraction and projection

def contract(g: SplitGraph, labels: DataFrame) -> tuple[SplitGraph, DataFrame]:
    """The graph of clusters, each named by its least member, and parent (id, coarse)."""
    names = labels.groupBy("label").agg(F.min("id").alias("coarse"), F.sum("w").alias("cw"))
    parent = spill(labels.join(names, "label").select("id", "coarse"), "parent", moved=F.count_if(F.col("id") != F.col("coarse")), rows=F.count(F.lit(1)))
    nodes = spill(names.select(F.col("coarse").alias("id"), F.col("cw").alias("w")), "nodes")
    a, b = parent.select(F.col("id").alias("src"), F.col("coarse").alias("a")), parent.select(F.col("id").alias("dst"), F.col("coarse").alias("b"))
    edges = g.edges.join(a, "src").join(b, "dst").where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("w").alias("w"))
    return SplitGraph(nodes, spill(edges, "edges")), parent


def project(parent: DataFrame, part: DataFrame) -> DataFrame:
    """(id, block) of the fine graph from (id, block) of the coarse one."""
    return parent.join(part.select(F.col("id").alias("coarse"), "block"), "coarse").select("id", "block")


def induced(g: SplitGraph, part: DataFrame) -> DataFrame:
    """Edges with both ends in one block: (block, src, dst, w)."""
    a, b = part.select(F.col("id").alias("src"), "block"), part.select(F.col("id").alias("dst"), F.col("block").alias("other"))
    return g.edges.join(a, "src").join(b, "dst").where("block = other").select("block", "src", "dst", "w")


# ---------------------------------------------------------------- blocks

def _labelled(g: SplitGraph, part: DataFrame) -> DataFrame:
    return g.nodes.join(part, "id").select("id", "w", F.col("block").cast("long").alias("label"))


def independent(moves: DataFrame, edges: DataFrame, seed: int) -> DataFrame:
    """Moves (id, gain, ...) without those next to a move of larger (gain, hash, id); then gains add up exactly."""
    key = moves.select("id", F.struct("gain", mix("id", seed).alias("h"), "id").alias("key"))
    own, other = key.select(F.col("id").alias("src"), F.col("key").alias("k1")), key.select(F.col("id").alias("dst"), F.col("key").alias("k2"))
    lost = edges.join(own, "src").join(other, "dst").where("k2 > k1").select(F.col("src").alias("id")).distinct()
    return moves.join(lost, "id", "left_anti")


def refine(g: SplitGraph, part: DataFrame, caps: DataFrame, rounds: int = 5, count: int = 4, order: str = "random", seed: int = 0, conflict: bool = True) -> DataFrame:
    """(id, block): propagation among blocks (block, cap) with strict limits; the cut never rises."""
    labels = spill(_labelled(g, part).join(classes(g.nodes, g.edges, order, count, seed), "id"), "blocks")
    limit = small(caps.select(F.col("block").cast("long").alias("label"), "cap"))
    for r in range(rounds):
        moved = False
        for c in range(count):
            own = g.edges.join(labels.where(F.col("cls") == c).select(F.col("id").alias("dst")), "dst", "left_semi")
            rated = ratings(own, labels)
            held = limit.join(label_weights(labels), "label", "left").select("label", (F.col("cap") - F.coalesce("held", F.lit(0))).alias("room"), F.coalesce("held", F.lit(0)).alias("held"))
            rows = rated.join(small(held), "label").join(labels.select("id", "w", F.col("label").alias("mine")), "id")
            stay = F.coalesce(F.max(F.when(F.col("label") == F.col("mine"), F.col("rate"))), F.lit(0))
            best = rows.groupBy("id", "w", "mine").agg(F.max_by(F.struct("label", "rate", "room", "held"), F.when((F.col("label") != F.col("mine")) & (F.col("w") <= F.col("room")), F.struct("rate", mix("label", seed + r).alias("t"), "label"))).alias("b"), stay.alias("stay"))
            source = held.select(F.col("label").alias("mine"), F.col("held").alias("source"))
            wish = best.where("b is not null").join(small(source), "mine").select("id", "mine", F.col("b.label").alias("target"), (F.col("b.rate") - F.col("stay")).alias("gain"), "w", F.col("b.room").alias("room"), (F.col("b.held") + F.col("w") < F.col("source")).alias("evens"))
            wish = wish.where("gain > 0 or (gain = 0 and evens)")
            wish = independent(wish, own, seed + r) if conflict else wish
            granted = admit(wish.select("id", "target", "gain", "w", "room"), "strict", seed + r).select("id", "target")
            # A block keeps at least one node: if all would leave, none does.
            count_in = labels.groupBy("label").agg(F.count(F.lit(1)).alias("members"))
            leaving = granted.join(labels.select("id", "label"), "id")
            emptied = leaving.groupBy("label").agg(F.count(F.lit(1)).alias("go")).join(count_in, "label").where("go >= members").select("label")
            moves = spill(leaving.join(small(emptied), "label", "left_anti").select("id", "target"), "moves")
            if not moves.take(1):
                continue
            moved = True
            after = spill(labels.join(moves, "id", "left").select("id", "w", F.coalesce("target", "label").alias("label"), "cls"), "blocks")
            release(labels, moves)
            labels = after
        if not moved:
            break
    return labels.select("id", F.col("label").cast("int").alias("block"))


def overload(g: SplitGraph, part: DataFrame, caps: DataFrame) -> DataFrame:
    """(block, held, cap, over) of every block."""
    held = g.nodes.join(part, "id").groupBy("block").agg(F.sum("w").alias("held"))
    return caps.join(held, "block", "left").select("block", F.coalesce("held", F.lit(0)).alias("held"), "cap", F.greatest(F.lit(0.0), F.coalesce("held", F.lit(0)) - F.col("cap")).alias("over"))


def candidates(g: SplitGraph, part: DataFrame, state: DataFrame, tried: DataFrame | None, seed: int) -> DataFrame:
    """Nodes of overloaded blocks with their best block that has room: (id, w, block, target, d, key, room, over)."""
    heavy = small(state.where("over > 0").select("block", "over"))
    rows = g.nodes.join(part, "id").join(heavy, "block")
    if tried is not None:
        rows = rows.join(tried, "id", "left_anti")
    own = g.edges.join(rows.select(F.col("id").alias("dst")), "dst", "left_semi")
    rated = ratings(own, part.withColumn("label", F.col("block").cast("long"))).join(rows, "id", "right")
    room = small(state.select(F.col("block").cast("long").alias("label"), (F.col("cap") - F.col("held")).alias("room")))
    rated = rated.join(room, "label", "left")
    external = (F.col("label") != F.col("block")) & (F.col("w") <= F.col("room"))
    best = rated.groupBy("id", "w", "block", "over").agg(F.max_by(F.struct("label", "rate", "room"), F.when(external, F.struct("rate", mix(F.coalesce("label", F.lit(0)), seed).alias("t"), "label"))).alias("b"), F.coalesce(F.max(F.when(F.col("label") == F.col("block"), F.col("rate"))), F.lit(0)).alias("inner"))
    # Interior or hemmed-in nodes go to a block with room picked by hash.
    open_ = state.where("held < cap").select("block", (F.col("cap") - F.col("held")).alias("room2")).withColumn("i", F.row_number().over(W.orderBy("block")) - 1).withColumn("of", F.count(F.lit(1)).over(W.partitionBy()))
    total = F.broadcast(open_.agg(F.count(F.lit(1)).alias("of")))
    best = best.crossJoin(total).withColumn("i", F.when(F.col("of") > 0, mix("id", seed) % F.greatest("of", F.lit(1))))
    best = best.join(small(open_.select("i", F.col("block").alias("any"), "room2")), "i", "left")
    d = F.when(F.col("b").isNotNull(), F.col("b.rate") - F.col("inner")).otherwise(-F.col("inner")).cast("double")
    target = F.coalesce(F.col("b.label"), F.when(F.col("w") <= F.col("room2"), F.col("any").cast("long")))
    out = best.select("id", "w", "block", "over", target.alias("target"), d.alias("d"), F.coalesce(F.col("b.room"), F.col("room2")).alias("room")).where("target is not null")
    return out.withColumn("key", F.when(F.col("d") >= 0, F.col("d") * F.col("w")).otherwise(F.col("d") / F.col("w")))


def prefix(rows: DataFrame, seed: int) -> DataFrame:
    """Best rows of each overloaded block whose weight just covers its overload."""
    ordered = in_order(rows, [F.col("block"), F.desc("key"), mix("id", seed), F.col("id")])
    sums = rows.groupBy("block").agg(F.sum("w").alias("_s"))
    start = sums.select("block", (F.sum("_s").over(W.orderBy("block")) - F.col("_s")).alias("_start"))
    return ordered.join(small(start), "block").where(F.col("before") - F.col("_start") < F.col("over")).drop("before", "_start")


def balance(g: SplitGraph, part: DataFrame, caps: DataFrame, rounds: int = 8, seed: int = 0) -> DataFrame:
    """(id, block) with no block above its cap (block, cap, share); residues are filled by running weight into running room."""
    part, tried = spill(part, "part"), None
    for r in range(rounds):
        state = spill(overload(g, part, caps), "state")
        if not state.where("over > 0").take(1):
            return part
        chosen = prefix(candidates(g, part, state, tried, seed + r), seed + r)
        moves = spill(admit(chosen.select("id", "target", F.col("key").alias("gain"), "w", "room"), "strict", seed + r).select("id", "target"), "moves")
        if not moves.take(1):
            break
        part = spill(part.join(moves, "id", "left").select("id", F.coalesce(F.col("target").cast("int"), F.col("block")).alias("block")), "part")
        tried = moves.select("id") if tried is None else tried.unionByName(moves.select("id"))
    return fill(g, part, caps)


def fill(g: SplitGraph, part: DataFrame, caps: DataFrame) -> DataFrame:
    """Place the excess of overloaded blocks: its running weight against the others' running deficit below their share.

    A block passes its share by at most one node, so it stays within its relaxed limit; the deficits together hold any excess.
    """
    held = g.nodes.join(part, "id").groupBy("block").agg(F.sum("w").alias("held"))
    state = spill(caps.join(held, "block", "left").select("block", "cap", "share", F.coalesce("held", F.lit(0)).alias("held")), "state")
    heavy = small(state.where("held > cap").select("block", F.col("share").alias("keep")))
    rows = g.nodes.join(part, "id").join(heavy, "block")
    excess = spill(running_weight(rows, ("block",)).where("upto > keep").select("id", "w"), "excess")
    excess = running_weight(excess, seed=1).select("id", (F.col("upto") - F.col("w")).cast("double").alias("at"))
    light = state.where("held < share").select("block", (F.col("share") - F.col("held")).alias("gap"))
    length = light.agg(F.sum("gap")).first()[0] or 0.0
    light = light.withColumn("to", F.sum("gap").over(W.orderBy("block"))).withColumn("from", F.col("to") - F.col("gap"))
    placed = at_positions(excess, light.select(F.col("block").alias("target"), "from", "to"), length).select("id", "target")
    return spill(part.join(placed, "id", "left").select("id", F.coalesce("target", "block").alias("block")), "part")


def rearranged(g: SplitGraph) -> tuple[SplitGraph, DataFrame]:
    """The graph with ids 0 .. n - 1 in order of degree bucket, and (id, bucket, new)."""
    degree = g.nodes.join(g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d")), "id", "left")
    rows = degree.select("id", "w", F.when(F.col("d") > 0, F.length(F.bin("d")) - 1).otherwise(F.lit(-1)).alias("bucket"))
    named = in_order(rows.withColumn("one", F.lit(1).cast("long")), [F.col("bucket"), F.col("id")], "one")
    names = spill(named.select("id", "w", "bucket", F.col("before").alias("new")), "names")
    a, b = names.select(F.col("id").alias("src"), F.col("new").alias("a")), names.select(F.col("id").alias("dst"), F.col("new").alias("b"))
    edges = g.edges.join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return SplitGraph(names.select(F.col("new").alias("id"), "w"), edges), names.drop("w")


# ---------------------------------------------------------------- rival steps

def match_round(g: SplitGraph, free: DataFrame, cap: float, seed: int) -> DataFrame:
    """(a, b): mutual heaviest proposals among free nodes (id, w) whose weight together fits the cap."""
    s, t = free.select(F.col("id").alias("src"), F.col("w").alias("ws")), free.select(F.col("id").alias("dst"), F.col("w").alias("wt"))
    e = g.edges.join(s, "src").join(t, "dst").where(F.col("ws") + F.col("wt") <= cap)
    best = e.groupBy("src").agg(F.max_by("dst", F.struct("w", mix(F.col("src").bitwiseXOR(F.col("dst")), seed).alias("t"), F.least("src", "dst").alias("l"))).alias("to"))
    back = best.select(F.col("src").alias("to"), F.col("to").alias("back"))
    return best.join(back, "to").where("back = src and src < to").select(F.col("src").alias("a"), F.col("to").alias("b"))


def match_heavy_edge(g: SplitGraph, cap: float, rounds: int = 4, seed: int = 0) -> DataFrame:
    """(id, w, label): pairs of heavy-edge matching as clusters."""
    labels = g.nodes.select("id", "w", F.col("id").alias("label"), F.lit(False).alias("taken"))
    for r in range(rounds):
        labels = spill(labels, "match")
        pairs = match_round(g, labels.where("not taken").select("id", "w"), cap, seed + r)
        into = pairs.select(F.col("b").alias("id"), F.col("a").alias("into")).unionByName(pairs.select(F.col("a").alias("id"), F.col("a").alias("into")))
        into = spill(into, "pairs")
        if not into.take(1):
            break
        labels = labels.join(into, "id", "left").select("id", "w", F.coalesce("into", "label").alias("label"), (F.col("taken") | F.col("into").isNotNull()).alias("taken"))
    return labels.select("id", "w", "label")


def match_two_hop(g: SplitGraph, matched: DataFrame, cap: float, seed: int = 0) -> DataFrame:
    """(id, w, label): single nodes of a matching (id, w, label) paired if they share their heaviest neighbour."""
    heaviest = g.edges.groupBy(F.col("src").alias("id")).agg(F.max_by("dst", F.struct("w", mix("dst", seed).alias("t"), "dst")).alias("fav"))
    # The favourite stays the neighbour itself, whatever cluster it is in, so labels of single nodes are its own.
    held = matched.join(heaviest, "id", "left").select("id", "w", "label", "fav")
    return two_hop(held, 0, cap, seed=seed)
