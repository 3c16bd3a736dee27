"""Queries over the given tables, each with SQL that derives the same rows independently.

Exact queries are compared row by row.  Algorithms are compared by certificates: facts that any right partition shows and that SQL derives from
the tables without running a partitioner.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import rules
from ..functions.hashing import mix, mix_sql
from ..model import SplitGraph, both_ways, from_edges
from ..operators import supersteps
from ..operators.local import Options
from ..sources import synth, tables
from ..storage import spill, table
from . import measures, partitioner, stats

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        ORACLES[name] = sql


def with_graph(graph: str, sql: str) -> str:
    """SQL with the views e (undirected), d (both ways) and v (nodes of weight 1) of a graph."""
    head, rest = f"WITH e AS ({tables.SQL.get(graph) or synth.SQL[graph]}), d AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e), v AS (SELECT DISTINCT src AS id, 1 AS w FROM d)", sql
    return head + (", " + rest[5:] if rest.startswith("WITH ") else " " + rest)


# ---------------------------------------------------------------- builders and generators

for _name, _build in tables.GRAPHS.items():
    register(f"build_{_name}", _build, tables.SQL[_name])
register("build_page_links", tables.page_links, tables.SQL["page_links"])
register("build_conv_words", tables.conv_words, tables.SQL["conv_words"])
register("build_page_links_whole", lambda s, d: tables.page_links(s, d, None), tables.SQL["page_links_whole"])
register("build_conv_words_whole", lambda s, d: tables.conv_words(s, d, None), tables.SQL["conv_words_whole"])
register("build_doc_lines_whole", tables.doc_lines_whole, tables.SQL["doc_lines_whole"])
register("vec_knn_edges", tables.vec_knn, tables.SQL["vec_knn"])
for _name, _make in synth.FIXTURES.items():
    register(f"gen_{_name}", lambda spark, d, make=_make: make(spark), synth.SQL[_name])


def event_hour_graph(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, hour, w): events of a user in an hour, a bipartite graph of users and hours."""
    return table(spark, d, "events").groupBy("user_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count(F.lit(1)).alias("w"))


register("event_hour_graph", event_hour_graph, "SELECT user_id, date_trunc('hour', ts) AS hour, count(*) AS w FROM events GROUP BY 1, 2")


def event_props_graph(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, event_type, w): weights from a JSON field."""
    e = table(spark, d, "events").select("user_id", "event_type", F.from_json("props", "k long")["k"].alias("k"))
    return e.groupBy("user_id", "event_type").agg(F.sum("k").alias("w"))


register("event_props_graph", event_props_graph, "SELECT user_id, event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS w FROM events GROUP BY 1, 2")


def asof_prev_event(spark: SparkSession, d: str) -> DataFrame:
    """(event_id, prev_id): the last earlier event of the same user within 30 minutes."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts")
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    out = e.withColumn("prev_id", F.lag("event_id").over(w)).withColumn("prev_ts", F.lag("ts").over(w))
    return out.where(F.col("ts") - F.col("prev_ts") <= F.expr("interval 30 minutes")).select("event_id", "prev_id")


_ASOF = "SELECT event_id, prev_id FROM (SELECT event_id, ts, lag(event_id) OVER w AS prev_id, lag(ts) OVER w AS prev_ts FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE ts - prev_ts <= INTERVAL 30 MINUTE"
register("asof_prev_event", asof_prev_event, _ASOF)


def build_session_edges(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst, w): event types that follow each other within a session."""
    t = table(spark, d, "events").select("event_id", "event_type")
    p = asof_prev_event(spark, d)
    named = p.join(t, "event_id").withColumnRenamed("event_type", "dst").join(t.select(F.col("event_id").alias("prev_id"), F.col("event_type").alias("src")), "prev_id")
    return named.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))


register("build_session_edges", build_session_edges, f"WITH p AS ({_ASOF}) SELECT a.event_type AS src, b.event_type AS dst, count(*) AS w FROM p JOIN events b ON b.event_id = p.event_id JOIN events a ON a.event_id = p.prev_id GROUP BY 1, 2")


# ---------------------------------------------------------------- formulas

def _params(spark: SparkSession, d: str) -> DataFrame:
    """Parameter rows from the nations: total, k, eps, heaviest, n, c, p."""
    i = F.col("n_nationkey").cast("long")
    return table(spark, d, "nation").select(i.alias("i"), (1000 + i * 37).alias("total"), (i % 7 + 2).alias("k"), (i % 3 + 1).alias("e"), (i % 50 + 1).alias("top"), (i * i * 97 + 300).alias("n"), (i % 4 * 100 + 50).alias("c"))


_PARAMS = "SELECT CAST(n_nationkey AS BIGINT) AS i, 1000 + n_nationkey * 37 AS total, n_nationkey % 7 + 2 AS k, n_nationkey % 3 + 1 AS e, n_nationkey % 50 + 1 AS top, n_nationkey * n_nationkey * 97 + 300 AS n, n_nationkey % 4 * 100 + 50 AS c FROM nation"


def formula_limits(spark: SparkSession, d: str) -> DataFrame:
    eps = F.col("e") / 100
    return _params(spark, d).select("i", F.round(F.greatest((1 + eps) * F.col("total") / F.col("k"), F.col("total") / F.col("k") + F.col("top")), 6).alias("relaxed"), F.round((1 + eps) * F.ceil(F.col("total") / F.col("k")), 6).alias("strict"))


register("formula_limits", formula_limits, f"SELECT i, round(greatest((1 + e / 100.0::DOUBLE) * total / k, total / k::DOUBLE + top), 6) AS relaxed, round((1 + e / 100.0::DOUBLE) * ceil(total / k), 6) AS strict FROM ({_PARAMS})")


def eps_table(spark: SparkSession, d: str) -> DataFrame:
    """(i, eps): slack of the first bisection, for blocks a little above and below their share."""
    part = F.col("total") * (90 + F.col("i")) / 100
    depth = F.greatest(F.lit(1.0), F.ceil(F.log2(F.col("k").cast("double"))).cast("double"))
    raw = F.pow((1 + F.col("e") / 100) * F.col("total") / part, 1 / depth) - 1
    return _params(spark, d).select("i", F.round(F.greatest(F.lit(0.0), raw), 6).alias("eps"))


register("eps_table", eps_table, f"SELECT i, round(greatest(0.0::DOUBLE, pow((1 + e / 100.0::DOUBLE) * total / (total * (90 + i) / 100.0::DOUBLE), 1 / greatest(1.0::DOUBLE, ceil(log2(k::DOUBLE)))) - 1), 6) AS eps FROM ({_PARAMS})")


def level_blocks_table(spark: SparkSession, d: str) -> DataFrame:
    bits = F.length(F.bin(F.greatest(F.ceil(F.col("n") / F.col("c")), F.lit(1)).cast("long") - 1))
    up = F.when(F.col("n") <= F.col("c"), F.lit(1)).otherwise(F.pow(F.lit(2.0), bits)).cast("long")
    return _params(spark, d).select("i", F.greatest(F.least(F.col("k"), F.lit(2)), F.least(F.col("k"), up)).cast("long").alias("blocks"))


register("level_blocks_table", level_blocks_table, f"SELECT i, CAST(greatest(least(k, 2), least(k, CASE WHEN n <= c THEN 1 ELSE pow(2, ceil(log2(ceil(n / c)))) END)) AS BIGINT) AS blocks FROM ({_PARAMS})")


def cluster_cap_table(spark: SparkSession, d: str) -> DataFrame:
    """(i, cap): cluster bound on a level of n div 3 nodes of a graph with n; the block number halves until the level is large enough."""
    b0 = F.least(F.col("k").cast("double"), F.col("n") / F.col("c"))
    now = F.expr("n div 3")
    # Halvings needed for now > b * c / 2, with b never below one before a halving.
    need = F.when(now <= b0 * F.col("c") / 2, F.floor(F.log2(b0 * F.col("c") / 2 / now)) + 1).otherwise(F.lit(0))
    most = F.when(b0 > 1, F.ceil(F.log2(b0))).otherwise(F.lit(0))
    b = b0 / F.pow(F.lit(2.0), F.least(need, most).cast("double"))
    return _params(spark, d).select("i", F.round(F.col("e") / 100 * F.col("total") / F.greatest(b, F.lit(1.0)), 6).alias("cap"))


register("cluster_cap_table", cluster_cap_table, f"""WITH RECURSIVE p AS ({_PARAMS}), h AS (SELECT i, e, total, n // 3 AS now, c, least(k::DOUBLE, n / c::DOUBLE) AS b FROM p UNION ALL SELECT i, e, total, now, c, b / 2 FROM h WHERE b > 1 AND now <= b * c / 2)
SELECT i, round(e / 100.0::DOUBLE * total / greatest(min(b), 1), 6) AS cap FROM h GROUP BY i, e, total""")


def split_counts(spark: SparkSession, d: str) -> DataFrame:
    """(k, f, n): after as many splits as floor2(k) allows, how many blocks still become f final ones."""
    k = table(spark, d, "nation").select((F.col("n_nationkey") + 2).cast("long").alias("k"))
    low = F.pow(F.lit(2.0), F.length(F.bin("k")) - 1).cast("long")
    return k.select("k", F.explode(F.array(F.struct(F.lit(2).cast("long").alias("f"), (F.col("k") - low).alias("n")), F.struct(F.lit(1).cast("long").alias("f"), (2 * low - F.col("k")).alias("n")))).alias("x")).select("k", "x.f", "x.n").where("n > 0")


register("split_counts", split_counts, """WITH RECURSIVE s AS (SELECT CAST(n_nationkey + 2 AS BIGINT) AS k, CAST(n_nationkey + 2 AS BIGINT) AS f, 0 AS depth FROM nation
UNION ALL SELECT k, CASE WHEN x = 0 THEN f // 2 ELSE f - f // 2 END, depth + 1 FROM s, range(2) t(x) WHERE depth < CAST(floor(log2(k)) AS INT)) SELECT k, f, count(*) AS n FROM s WHERE depth = CAST(floor(log2(k)) AS INT) GROUP BY k, f""")


def relative_gain_table(spark: SparkSession, d: str) -> DataFrame:
    return _params(spark, d).select("i", F.round(rules.relative_gain((F.col("i") - 12).cast("double"), F.col("top")), 6).alias("gain"))


register("relative_gain_table", relative_gain_table, f"SELECT i, round(CASE WHEN i >= 12 THEN (i - 12)::DOUBLE * top ELSE (i - 12)::DOUBLE / top END, 6) AS gain FROM ({_PARAMS})")


def predicted_cost_table(spark: SparkSession, d: str) -> DataFrame:
    n, p = F.col("n").cast("double"), F.lit(10.0)
    one = n / p * F.greatest(F.lit(1.0), F.log2(F.col("k") * F.col("c") / n)) + F.log2(n) * F.log2(n)
    two = n / p + F.col("k") * F.col("c") * F.log2(F.col("k").cast("double")) + F.log2(n) * F.log2(n)
    rec = F.log2(F.col("k").cast("double")) * (n / p + F.log2(n) * F.log2(n))
    return _params(spark, d).select("i", F.round(one, 4).alias("one_cycle"), F.round(two, 4).alias("direct"), F.round(rec, 4).alias("recursive"))


register("predicted_cost_table", predicted_cost_table, f"SELECT i, round(n / 10.0::DOUBLE * greatest(1.0::DOUBLE, log2(k * c / n::DOUBLE)) + log2(n) * log2(n), 4) AS one_cycle, round(n / 10.0::DOUBLE + k * c * log2(k::DOUBLE) + log2(n) * log2(n), 4) AS direct, round(log2(k::DOUBLE) * (n / 10.0::DOUBLE + log2(n) * log2(n)), 4) AS recursive FROM ({_PARAMS})")


# ---------------------------------------------------------------- facts and measures on given partitions

def _mod(g: SplitGraph, graph: str, k: int = 4) -> DataFrame:
    """Blocks by id; for two-sided graphs by key, so that both sides spread."""
    key = F.expr("id div 2") if graph in ("cust_part", "supp_part", "order_part") else F.col("id")
    return g.nodes.select("id", (key % k).cast("int").alias("block"))


def _mod_sql(graph: str, col: str = "id", k: int = 4) -> str:
    return f"({col} // 2) % {k}" if graph in ("cust_part", "supp_part", "order_part") else f"{col} % {k}"


for _g in tables.GRAPHS:
    register(f"describe_{_g}", lambda s, d, g=_g: measures.describe_graph(tables.load(s, d, g)), with_graph(_g, "SELECT (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m, (SELECT CAST(sum(w) AS BIGINT) FROM e) AS w, (SELECT max(c) FROM (SELECT count(*) AS c FROM d GROUP BY src)) AS max_deg"))
    register(f"edge_cut_{_g}_mod4", lambda s, d, g=_g: (lambda gr: measures.edge_cut(gr, _mod(gr, g)))(tables.load(s, d, g)), with_graph(_g, f"SELECT CAST(sum(w) AS BIGINT) AS cut FROM e WHERE {_mod_sql(_g, 'src')} <> {_mod_sql(_g, 'dst')}"))


def on(graph: str, fn: Callable[[SplitGraph], DataFrame], node_w: str | None = None) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: fn(tables.load(spark, d, graph, node_w))


register("imbalance_mod", on("user_next", lambda g: measures.imbalance(g, _mod(g, "user_next"), 4).select(F.round("imbalance", 6).alias("imbalance"))), with_graph("user_next", "SELECT round(max(n) * 4 / sum(n)::DOUBLE, 6) AS imbalance FROM (SELECT count(*) AS n FROM v GROUP BY id % 4)"))
register("feasible_mod", on("copurchase", lambda g: measures.is_feasible(g, _mod(g, "copurchase"), 4, 0.03).select("feasible", "heaviest_block", F.round("cap", 6).alias("cap"))), with_graph("copurchase", "SELECT max(n) <= greatest(1.03::DOUBLE * sum(n) / 4, sum(n) / 4.0::DOUBLE + 1) AS feasible, max(n) AS heaviest_block, round(greatest(1.03::DOUBLE * sum(n) / 4, sum(n) / 4.0::DOUBLE + 1), 6) AS cap FROM (SELECT count(*) AS n FROM v GROUP BY id % 4)"))
register("boundary_nodes", on("order_chain", lambda g: measures.boundary(g, _mod(g, "order_chain"))), with_graph("order_chain", "SELECT DISTINCT src AS id FROM d WHERE src % 4 <> dst % 4"))
register("external_degree", on("copurchase", lambda g: measures.external_degree(g, _mod(g, "copurchase"))), with_graph("copurchase", "SELECT CAST(src % 4 AS INTEGER) AS block, CAST(sum(w) AS BIGINT) AS external FROM d WHERE src % 4 <> dst % 4 GROUP BY 1"))
register("quotient_graph", on("doc_lines", lambda g: measures.quotient(g, _mod(g, "doc_lines"))), with_graph("doc_lines", "SELECT CAST(least(src % 4, dst % 4) AS INTEGER) AS a, CAST(greatest(src % 4, dst % 4) AS INTEGER) AS b, CAST(sum(w) AS BIGINT) AS w FROM e WHERE src % 4 <> dst % 4 GROUP BY 1, 2"))
register("comm_volume", on("user_next", lambda g: measures.comm_volume(g, _mod(g, "user_next"))), with_graph("user_next", "SELECT CAST(src % 4 AS INTEGER) AS block, count(*) AS volume FROM (SELECT DISTINCT src, dst % 4 AS b FROM d WHERE src % 4 <> dst % 4) GROUP BY 1"))
register("partition_diff", on("user_next", lambda g: measures.diff(_mod(g, "user_next", 4), _mod(g, "user_next", 3))), with_graph("user_next", "SELECT CAST(id % 4 AS INTEGER) AS old, CAST(id % 3 AS INTEGER) AS new, count(*) AS n FROM v GROUP BY 1, 2"))
_cutset = lambda g, k: measures.both_blocks(g.undirected(), g.nodes.select("id", (F.col("id") % k).alias("block"))).where("bs <> bd").select("src", "dst")
register("cut_sets_intersect", on("user_next", lambda g: _cutset(g, 4).intersect(_cutset(g, 3))), with_graph("user_next", "SELECT src, dst FROM e WHERE src % 4 <> dst % 4 AND src % 3 <> dst % 3"))
register("cut_sets_except", on("user_next", lambda g: _cutset(g, 4).exceptAll(_cutset(g, 3))), with_graph("user_next", "SELECT src, dst FROM e WHERE src % 4 <> dst % 4 AND src % 3 = dst % 3"))
register("degree_buckets", on("copurchase", lambda g: g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d")).groupBy((F.length(F.bin("d")) - 1).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))), with_graph("copurchase", "SELECT CAST(floor(log2(c)) AS INTEGER) AS bucket, count(*) AS n FROM (SELECT count(*) AS c FROM d GROUP BY src) GROUP BY 1"))
register("cut_edges_mod4", on("nation_trade", lambda g: measures.both_blocks(g.undirected(), _mod(g, "nation_trade")).where("bs <> bd").select("src", "dst", "w")), with_graph("nation_trade", "SELECT src, dst, w FROM e WHERE src % 4 <> dst % 4"))
register("induced_edges_mod4", on("nation_trade", lambda g: supersteps.induced(g, _mod(g, "nation_trade"))), with_graph("nation_trade", "SELECT CAST(src % 4 AS INTEGER) AS block, src, dst, w FROM d WHERE src % 4 = dst % 4"))
register("edges_symmetrized", lambda s, d: both_ways(tables.user_next(s, d)), with_graph("user_next", "SELECT src, dst, w FROM d"))
register("adjacency_lists", on("nation_trade", lambda g: g.edges.groupBy("src").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("dst", "w"))), lambda x: F.concat_ws(":", x["dst"].cast("string"), x["w"].cast("string"))), ",").alias("adj"))), with_graph("nation_trade", "SELECT src, string_agg(dst || ':' || w, ',' ORDER BY dst) AS adj FROM d GROUP BY src"))


def degree_with_isolated(spark: SparkSession, d: str) -> DataFrame:
    """(id, d): orders with their number of parts, none included."""
    g = from_edges(tables.order_part(spark, d))
    deg = g.edges.where("src % 2 = 0").groupBy(F.expr("src div 2").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    return table(spark, d, "orders").select(F.col("o_orderkey").alias("id")).join(deg, "id", "left").select("id", F.coalesce("d", F.lit(0)).alias("d"))


register("degree_with_isolated", degree_with_isolated, "SELECT o_orderkey AS id, count(DISTINCT l_partkey) AS d FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
register("isolated_orders", lambda s, d: table(s, d, "orders").select(F.col("o_orderkey").alias("id")).join(table(s, d, "lineitem").select(F.col("l_orderkey").alias("id")), "id", "left_anti"), "SELECT o_orderkey AS id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
register("components", lambda s, d: supersteps_components(tables.load(s, d, "doc_lines")), with_graph("doc_lines", "SELECT 1").replace("WITH e AS", "WITH RECURSIVE e AS").replace(" SELECT 1", ", r AS (SELECT id, id AS c FROM v UNION SELECT d.dst, r.c FROM r JOIN d ON d.src = r.id WHERE r.c < d.dst) SELECT id, min(c) AS component FROM r GROUP BY id"))


def supersteps_components(g: SplitGraph) -> DataFrame:
    """(id, component): labels spread to the least neighbour and are followed, until none changes."""
    label = spill(g.nodes.select("id", F.col("id").alias("component")), "component")
    while True:
        low = g.edges.join(label.select(F.col("id").alias("src"), "component"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("component").alias("near"))
        step = label.join(low, "id", "left").select("id", F.least("component", F.coalesce("near", "component")).alias("next"), "component")
        jump = step.select(F.col("id").alias("at"), F.col("next").alias("far"))
        after = spill(step.join(jump, step["next"] == jump["at"]).select("id", F.col("far").alias("component"), (F.col("far") != F.col("component")).alias("moved")), "component")
        label = after.select("id", "component")
        if not after.where("moved").take(1):
            return label


# ---------------------------------------------------------------- single steps

def _mod_labels(g: SplitGraph, k: int) -> DataFrame:
    return g.nodes.select("id", "w", (F.col("id") % k).alias("label"))


register("lp_ratings", on("user_next", lambda g: supersteps.ratings(g.edges, _mod_labels(g, 8))), with_graph("user_next", "SELECT dst AS id, src % 8 AS label, CAST(sum(w) AS BIGINT) AS rate FROM d GROUP BY 1, 2"))
_P1 = f"""WITH r AS (SELECT d.dst AS id, d.src AS label, CAST(d.w AS BIGINT) AS rate, {mix_sql('d.src', 0)} AS t FROM d),
b AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY rate DESC, t DESC, label DESC) AS n FROM r)"""
_start = lambda g: g.nodes.select("id", "w", F.col("id").alias("label"))
register("lp_round1_best", on("doc_lines", lambda g: supersteps.propose(g.edges, _start(g), 5.0, 0).where("target is not null").select("id", "target", "gain")), with_graph("doc_lines", _P1 + " SELECT id, label AS target, rate AS gain FROM b WHERE n = 1"))
register("lp_favourite", on("doc_lines", lambda g: supersteps.propose(g.edges, _mod_labels(g, 16), 30.0, 0).where("fav is not null").select("id", "fav")), with_graph("doc_lines", f"""WITH h AS (SELECT id % 16 AS label, count(*) AS held FROM v GROUP BY 1), r AS (SELECT d.dst AS id, d.src % 16 AS label, sum(d.w) AS rate FROM d GROUP BY 1, 2),
b AS (SELECT r.*, held, row_number() OVER (PARTITION BY id ORDER BY rate DESC, {mix_sql('r.label', 0)} DESC, r.label DESC) AS n FROM r JOIN h USING (label)) SELECT id, label AS fav FROM b WHERE n = 1 AND label <> id % 16 AND held + 1 > 30"""))


def lp_two_rounds(g: SplitGraph) -> DataFrame:
    """(id, label) after two soft rounds with one class: all nodes act on the labels of the round's start."""
    found = supersteps.lp_cluster(g, float("inf"), rounds=2, count=1, order="id", enforce="soft", active=False, seed=0)
    return found.select("id", "label")


def _lp_sql(prev: str, out: str, seed: int) -> str:
    return f"""{out}r AS (SELECT d.dst AS id, p.label, CAST(sum(d.w) AS BIGINT) AS rate FROM d JOIN {prev} p ON p.id = d.src GROUP BY 1, 2),
{out}b AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY rate DESC, {mix_sql('label', seed)} DESC, label DESC) AS n FROM {out}r),
{out} AS (SELECT p.id, CASE WHEN b.label <> p.label AND (b.rate > coalesce(s.rate, 0) OR (b.rate = coalesce(s.rate, 0) AND {mix_sql('b.label', seed)} > {mix_sql('p.label', seed)})) THEN b.label ELSE p.label END AS label
  FROM {prev} p LEFT JOIN {out}b b ON b.id = p.id AND b.n = 1 LEFT JOIN {out}r s ON s.id = p.id AND s.label = p.label)"""


register("lp_two_rounds", on("user_next", lp_two_rounds), with_graph("user_next", f"WITH l0 AS (SELECT id, id AS label FROM v), {_lp_sql('l0', 'l1', 0)}, {_lp_sql('l1', 'l2', 1)} SELECT id, label FROM l2"))


def _proposals(g: SplitGraph) -> DataFrame:
    return g.nodes.select("id", (F.col("id") % 5).alias("target"), (mix("id", 3) % 100).alias("gain"), (F.col("id") % 7 + 1).alias("w"), F.lit(60).cast("long").alias("room"))


_PROPOSALS = f"SELECT id, id % 5 AS target, {mix_sql('id', 3)} % 100 AS gain, id % 7 + 1 AS w, 60 AS room FROM v"
register("strict_admission", on("user_next", lambda g: supersteps.admit(_proposals(g), "strict", 1).select("id", "target")), with_graph("user_next", f"SELECT id, target FROM (SELECT *, sum(w) OVER (PARTITION BY target ORDER BY gain DESC, {mix_sql('id', 1)}, id) AS run FROM ({_PROPOSALS})) WHERE run <= room"))
register("sampled_admission", on("user_next", lambda g: supersteps.admit(_proposals(g), "sampled", 1).select("id", "target")), with_graph("user_next", f"SELECT id, target FROM (SELECT *, sum(w) OVER (PARTITION BY target) AS demand FROM ({_PROPOSALS})) WHERE {mix_sql('id', 1)} / 2147483647.0::DOUBLE < room / demand::DOUBLE"))
register("two_hop_pairs", on("user_next", lambda g: supersteps.two_hop(g.nodes.select("id", "w", F.col("id").alias("label"), (F.col("id") % 6).alias("fav")), 2, 2.0, seed=0).groupBy("label").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("n"))), with_graph("user_next", "WITH c AS (SELECT count(*) AS c FROM v GROUP BY id % 6), s AS (SELECT sum(c // 2) AS pairs, sum(c % 2) AS odd FROM c) SELECT CAST(2 AS BIGINT) AS size, CAST(pairs AS BIGINT) AS n FROM s WHERE pairs > 0 UNION ALL SELECT 1, CAST(odd AS BIGINT) FROM s WHERE odd > 0"))
register("contract_mod", on("user_next", lambda g: supersteps.contract(g, _mod_labels(g, 10))[0].undirected()), with_graph("user_next", "WITH n AS (SELECT id % 10 AS l, min(id) AS c FROM v GROUP BY 1) SELECT a.c AS src, b.c AS dst, CAST(sum(d.w) AS BIGINT) AS w FROM d JOIN n a ON a.l = d.src % 10 JOIN n b ON b.l = d.dst % 10 WHERE a.c < b.c GROUP BY 1, 2"))
register("contract_cut_invariant", on("doc_lines", lambda g: _cut_invariant(g)), "SELECT CAST(1 AS BIGINT) AS same_cut, CAST(1 AS BIGINT) AS same_weight")
register("project_labels", on("user_next", lambda g: (lambda c: supersteps.project(c[1], c[0].nodes.select("id", (F.col("id") % 3).cast("int").alias("block"))))(supersteps.contract(g, _mod_labels(g, 10)))), with_graph("user_next", "WITH n AS (SELECT id % 10 AS l, min(id) AS c FROM v GROUP BY 1) SELECT id, CAST(c % 3 AS INTEGER) AS block FROM v JOIN n ON l = id % 10"))
register("active_nodes", on("doc_lines", lambda g: supersteps.active_nodes(g.edges, g.nodes.where("id % 9 = 0").select("id"))), with_graph("doc_lines", "SELECT DISTINCT dst AS id FROM d WHERE src % 9 = 0"))
register("conflict_free_movers", on("doc_lines", lambda g: supersteps.independent(g.nodes.where("id % 2 = 0").select("id", (F.col("id") % 5).alias("gain")), g.edges, 0).select("id")), with_graph("doc_lines", f"WITH m AS (SELECT id, id % 5 AS gain, {mix_sql('id', 0)} AS h FROM v WHERE id % 2 = 0) SELECT id FROM m WHERE NOT EXISTS (SELECT 1 FROM d JOIN m o ON o.id = d.dst WHERE d.src = m.id AND (o.gain, o.h, o.id) > (m.gain, m.h, m.id))"))


def _cut_invariant(g: SplitGraph) -> DataFrame:
    coarse, parent = supersteps.contract(g, _mod_labels(g, 40))
    part = coarse.nodes.select("id", (mix("id", 2) % 4).cast("int").alias("block"))
    fine = supersteps.project(parent, part)
    a, b = measures.edge_cut(coarse, part).withColumnRenamed("cut", "a"), measures.edge_cut(g, fine).withColumnRenamed("cut", "b")
    w1, w2 = measures.block_weights(coarse, part).select("block", F.col("w").alias("x")), measures.block_weights(g, fine).select("block", F.col("w").alias("y"))
    same = w1.join(w2, "block", "full").agg(F.bool_and(F.col("x") == F.col("y")).cast("long").alias("same_weight"))
    return a.crossJoin(b).crossJoin(same).select((F.col("a") == F.col("b")).cast("long").alias("same_cut"), "same_weight")


def overload_prefix(g: SplitGraph) -> DataFrame:
    rows = g.nodes.select("id", (F.col("id") % 4).cast("int").alias("block"), (F.col("id") % 7 + 1).alias("w"), (mix("id", 5) % 50).cast("double").alias("key"), F.lit(15.0).alias("over"))
    return supersteps.prefix(rows, 0).select("id", "block")


register("overload_prefix", on("user_next", overload_prefix), with_graph("user_next", f"SELECT id, CAST(block AS INTEGER) AS block FROM (SELECT *, sum(w) OVER (PARTITION BY block ORDER BY key DESC, {mix_sql('id', 0)}, id) - w AS before FROM (SELECT id, id % 4 AS block, id % 7 + 1 AS w, {mix_sql('id', 5)} % 50 AS key FROM v)) WHERE before < 15"))
register("match_round1", on("user_next", lambda g: supersteps.match_round(g, g.nodes, 2.0, 0)), with_graph("user_next", f"WITH p AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY w DESC, {mix_sql('xor(src, dst)', 0)} DESC, least(src, dst) DESC) AS n FROM d) SELECT a.src AS a, a.dst AS b FROM p a JOIN p b ON b.src = a.dst AND b.dst = a.src WHERE a.n = 1 AND b.n = 1 AND a.src < a.dst"))

# ---------------------------------------------------------------- trivial rivals

_parts = lambda s, d: table(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("long").alias("w"))
_PARTS = "SELECT p_partkey AS id, CAST(p_size AS BIGINT) AS w FROM part"
register("mod_cut", lambda s, d: partitioner.mod_cut(_parts(s, d), 8), "SELECT p_partkey AS id, CAST(p_partkey % 8 AS INTEGER) AS block FROM part")
register("hash_cut", lambda s, d: partitioner.hash_cut(_parts(s, d), 8), f"SELECT p_partkey AS id, CAST({mix_sql('p_partkey', 0)} % 8 AS INTEGER) AS block FROM part")
register("range_cut", lambda s, d: partitioner.range_cut(_parts(s, d), 8), "SELECT p_partkey AS id, CAST((row_number() OVER (ORDER BY p_partkey) - 1) * 8 // (SELECT count(*) FROM part) AS INTEGER) AS block FROM part")
register("weight_fill_cut", lambda s, d: partitioner.weight_fill_cut(_parts(s, d), 8), f"SELECT id, CAST(least(7, before * 8 // total) AS INTEGER) AS block FROM (SELECT id, CAST(sum(w) OVER (ORDER BY id) - w AS BIGINT) AS before, CAST(sum(w) OVER () AS BIGINT) AS total FROM ({_PARTS}))")
register("snake_cut", lambda s, d: partitioner.snake_cut(_parts(s, d), 8), f"SELECT id, CAST(CASE WHEN r // 8 % 2 = 0 THEN r % 8 ELSE 7 - r % 8 END AS INTEGER) AS block FROM (SELECT id, row_number() OVER (ORDER BY w DESC, id) - 1 AS r FROM ({_PARTS}))")


# ---------------------------------------------------------------- partitions, by certificate

def certificate(graph: str, instances: list[dict], node_w: str | None = None, build=None) -> Callable[[SparkSession, str], DataFrame]:
    """(scheme, k, metric, value) of a batch of instances on one graph."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        g = tables.load_once(spark, d, graph, node_w) if build is None else from_edges(build(spark))
        g = g if build is None else SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
        parts = spill(partitioner.partition_many(g, [{x: y for x, y in i.items() if x not in ("name", "strict")} for i in instances]), "parts")
        c = measures.certify_many(g, parts, instances)
        values = {"nodes": "nodes", "assigned": "assigned", "distinct_ids": "distinct_ids", "blocks_used": "blocks_used", "node_weight": "node_weight", "edge_weight": "edge_weight", "over_relaxed": "over_relaxed", "cut_le_mod": "cast(cut <= mod_cut as bigint)"}
        return c.select("scheme", "k", F.explode(F.array(*[F.struct(F.lit(m).alias("metric"), F.expr(f"cast({v} as bigint)").alias("value")) for m, v in values.items()])).alias("r")).select("scheme", "k", "r.metric", "r.value")

    return run


def certificate_sql(graph: str, instances: list[dict], node_w: str | None = None) -> str:
    rows = ", ".join(f"('{i.get('name', i.get('scheme', 'one_cycle'))}', {i['k']})" for i in instances)
    weight = "(SELECT CAST(count(*) AS BIGINT) FROM d)" if node_w == "degree" else "n"
    return with_graph(graph, f"""WITH i(scheme, k) AS (VALUES {rows}), f AS (SELECT (SELECT count(*) FROM v) AS n, (SELECT CAST(sum(w) AS BIGINT) FROM e) AS m)
SELECT scheme, CAST(k AS INTEGER) AS k, x.metric, CAST(x.value AS BIGINT) AS value FROM i, f, LATERAL (VALUES ('nodes', n), ('assigned', n), ('distinct_ids', n), ('blocks_used', k), ('node_weight', {weight}), ('edge_weight', m), ('over_relaxed', 0), ('cut_le_mod', 1)) x(metric, value)""")


def certified(name: str, graph: str, instances: list[dict], node_w: str | None = None) -> None:
    build = synth.FIXTURES.get(graph) if graph in synth.FIXTURES else None
    register(name, certificate(graph, instances, node_w, build), certificate_sql(graph, instances, node_w))


SMALL_K = (2, 4, 8, 16, 32, 64)
FAST = {"tries": 1, "repeats": 1, "c": 200}
for _g in tables.GRAPHS:
    _ks = (2, 4, 8) if _g == "nation_trade" else SMALL_K
    certified(f"partition_{_g}", _g, [{"k": k, **FAST} for k in _ks])
certified("partition_general_k", "doc_lines", [{"k": k, **FAST} for k in (3, 5, 7, 11, 100)])
certified("partition_weighted", "doc_lines", [{"k": k, **FAST} for k in (2, 4, 8)], node_w="degree")
certified("partition_large_k", "copurchase", [{"k": k, **FAST, "c": 100} for k in (128, 256, 500)])
certified("partition_lanes", "doc_lines", [{"name": f"lanes{x}", "k": 8, "lanes": x, "c": 50} for x in (1, 2, 4)])
certified("partition_grid", "grid", [{"k": k, **FAST, "c": 50} for k in (2, 8, 64)])
certified("partition_torus", "torus", [{"k": k, **FAST, "c": 50} for k in (2, 8)])
certified("partition_planted", "planted", [{"k": k, **FAST, "c": 50} for k in (2, 8)])
certified("partition_powerlaw", "powerlaw", [{"k": k, **FAST} for k in (2, 16)])
certified("partition_eps", "doc_lines", [{"name": f"eps{e}", "k": 8, "eps": e, **FAST} for e in (0.01, 0.03, 0.1)])

_VARIANTS = {
    "enforce": ("soft", "strict", "sampled"), "order": ("bucket", "degree", "random", "id"), "active": (True, False), "final_order": ("once", "twice"), "two_hop": ("pairs", "groups", "off"),
    "adaptive": (True, False), "conflict": ("independent", "none"), "slack": ("adaptive", "fixed"),
}
for _option, _values in _VARIANTS.items():
    certified(f"variants_{_option}", "doc_lines", [{"name": f"{_option}_{v}", "k": 8, _option: v, "c": 60, "tries": 1} for v in _values])
certified("variants_pool", "doc_lines", [{"name": f"pool_{p}", "k": 8, "pool": (p,), "c": 60, "tries": 1} for p in ("random", "bfs", "grow")])


def rivals(graph: str) -> Callable[[SparkSession, str], DataFrame]:
    """(scheme, k, metric, value) for the rivals: what they promise is that every node has one of k blocks; balance is not promised by all."""
    schemes = ["direct_kway", "recursive_fixed", "recursive_adaptive", "kway_fm", "single_level_lp", "local_matching", "local_lp"]
    instances = [{"scheme": s, "k": k, **FAST, "c": 100} for s in schemes for k in (4, 16)]
    full = certificate(graph, instances)
    return lambda spark, d: full(spark, d).where("metric not in ('over_relaxed', 'blocks_used')")


def _rivals_sql(graph: str) -> str:
    schemes = ["direct_kway", "recursive_fixed", "recursive_adaptive", "kway_fm", "single_level_lp", "local_matching", "local_lp"]
    return f"SELECT * FROM ({certificate_sql(graph, [{'scheme': s, 'k': k} for s in schemes for k in (4, 16)])}) WHERE metric NOT IN ('over_relaxed', 'blocks_used')"


register("rivals_copurchase", rivals("copurchase"), _rivals_sql("copurchase"))
register("rivals_doc_lines", rivals("doc_lines"), _rivals_sql("doc_lines"))


def distributed(spark: SparkSession, d: str) -> DataFrame:
    """The superstep path, forced on a small graph: levels, splits by block, balance and refinement as frames."""
    g = tables.load(spark, d, "doc_lines")
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    part = partitioner.partition(g, 4, Options(c=100, rounds=1, classes=2, tries=1, repeats=1), mode="distributed", task_edges=4000)
    return measures.certify(g, spill(part, "part"), 4, mod=_mod(g, "doc_lines"))


register("partition_distributed", distributed, with_graph("doc_lines", """WITH f AS (SELECT (SELECT count(*) FROM v) AS n, (SELECT CAST(sum(w) AS BIGINT) FROM e) AS m)
SELECT x.metric, CAST(x.value AS BIGINT) AS value FROM f, LATERAL (VALUES ('nodes', n), ('assigned', n), ('distinct_ids', n), ('blocks_used', 4), ('blocks_in_range', 1), ('node_weight', n), ('edge_weight', m), ('over_relaxed', 0), ('cut_le_mod', 1), ('cut_plus_inner_ok', 1)) x(metric, value)"""))


def clustering_facts(g: SplitGraph, clusters: DataFrame, cap: float) -> DataFrame:
    """(nodes, weight, over, founded): a clustering covers all nodes, keeps the cap, and is named by nodes."""
    sizes = clusters.groupBy("label").agg(F.sum("w").alias("cw"))
    named = sizes.join(g.nodes.select(F.col("id").alias("label")), "label", "left_anti").agg(F.count(F.lit(1)).alias("unnamed"))
    return clusters.agg(F.count_distinct("id").alias("nodes"), F.sum("w").alias("weight")).crossJoin(sizes.agg(F.count_if(F.col("cw") > cap).alias("over"))).crossJoin(named)


for _g in ("user_next", "doc_lines"):
    register(f"cluster_{_g}", on(_g, lambda g: clustering_facts(g, supersteps.lp_cluster(g, 8, rounds=2, count=2), 8)), with_graph(_g, "SELECT (SELECT count(*) FROM v) AS nodes, (SELECT count(*) FROM v) AS weight, CAST(0 AS BIGINT) AS over, CAST(0 AS BIGINT) AS unnamed"))
register("unbounded_lp", on("doc_lines", lambda g: clustering_facts(g, supersteps.lp_cluster(g, float("inf"), rounds=1, count=2, enforce="soft"), float("inf"))), with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS nodes, (SELECT count(*) FROM v) AS weight, CAST(0 AS BIGINT) AS over, CAST(0 AS BIGINT) AS unnamed"))
register("heavy_edge_matching", on("doc_lines", lambda g: clustering_facts(g, supersteps.match_heavy_edge(g, 2.0, 2), 2)), with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS nodes, (SELECT count(*) FROM v) AS weight, CAST(0 AS BIGINT) AS over, CAST(0 AS BIGINT) AS unnamed"))

register("two_hop_matching", on("doc_lines", lambda g: clustering_facts(g, supersteps.match_two_hop(g, supersteps.match_heavy_edge(g, 2.0, 2), 2.0), 2)), with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS nodes, (SELECT count(*) FROM v) AS weight, CAST(0 AS BIGINT) AS over, CAST(0 AS BIGINT) AS unnamed"))


def coarsen_facts(g: SplitGraph) -> DataFrame:
    """(node_weight, edge_weight): kept by contraction, inner weight counted in."""
    labels = spill(supersteps.lp_cluster(g, 6, rounds=1, count=2).select("id", "w", "label"), "clusters")
    coarse, parent = supersteps.contract(g, labels)
    inner = measures.both_blocks(g.undirected(), parent.withColumnRenamed("coarse", "block")).where("bs = bd").agg(F.coalesce(F.sum("w"), F.lit(0)).alias("inner"))
    return coarse.nodes.agg(F.sum("w").alias("node_weight")).crossJoin(coarse.undirected().agg(F.sum("w").alias("outer"))).crossJoin(inner).select("node_weight", (F.col("outer") + F.col("inner")).alias("edge_weight"))


register("coarsen_user_next", on("user_next", coarsen_facts), with_graph("user_next", "SELECT (SELECT count(*) FROM v) AS node_weight, (SELECT CAST(sum(w) AS BIGINT) FROM e) AS edge_weight"))


def balance_from_one_block(g: SplitGraph) -> DataFrame:
    """(over, assigned): all nodes start in one of four blocks."""
    caps = partitioner.caps_of(g.nodes.sparkSession, {b: 1 for b in range(4)}, g.facts.weight, 4, 0.03, g.facts.heaviest)
    part = supersteps.balance(g, g.nodes.select("id", F.lit(0).alias("block")), caps, rounds=2)
    return supersteps.overload(g, part, caps).agg(F.count_if(F.col("over") > 0).alias("over")).crossJoin(part.agg(F.count_distinct("id").alias("assigned")))


register("balance_from_one_block", on("user_next", balance_from_one_block), with_graph("user_next", "SELECT CAST(0 AS BIGINT) AS over, (SELECT count(*) FROM v) AS assigned"))


def refine_facts(g: SplitGraph) -> DataFrame:
    """(no_worse, over): refinement from blocks by id lowers the cut or keeps it, and keeps the limits."""
    caps = partitioner.caps_of(g.nodes.sparkSession, {b: 1 for b in range(4)}, g.facts.weight, 4, 0.1, g.facts.heaviest)
    before = partitioner.range_cut(g.nodes, 4)
    after = spill(supersteps.refine(g, before, caps, rounds=2, count=2), "part")
    a, b = measures.edge_cut(g, before).withColumnRenamed("cut", "a"), measures.edge_cut(g, after).withColumnRenamed("cut", "b")
    return a.crossJoin(b).select((F.col("b") <= F.col("a")).cast("long").alias("no_worse")).crossJoin(supersteps.overload(g, after, caps).agg(F.count_if(F.col("over") > 0).alias("over")))


register("refine_user_next", on("user_next", refine_facts), "SELECT CAST(1 AS BIGINT) AS no_worse, CAST(0 AS BIGINT) AS over")


def known_cut(make: Callable, k: int, c: int = 10, bound: int | None = None) -> Callable[[SparkSession, str], DataFrame]:
    """(cut) of the scheme where the optimum is known; with ``bound``, (within) it."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        g = from_edges(make(spark))
        part = spill(partitioner.partition(g, k, Options(c=c, tries=4, repeats=4)), "part")
        cut = measures.edge_cut(g, part)
        return cut if bound is None else cut.select((F.col("cut") <= bound).cast("long").alias("within"))

    return run


register("cliques_zero_cut", known_cut(lambda s: synth.cliques(s, 8, 10), 8), "SELECT CAST(0 AS BIGINT) AS cut")
register("path_min_cut", known_cut(lambda s: synth.path(s, 64), 4), "SELECT CAST(3 AS BIGINT) AS cut")
register("ring_min_cut", known_cut(lambda s: synth.ring(s, 64), 4), "SELECT CAST(4 AS BIGINT) AS cut")
register("grid_cut_bound", known_cut(lambda s: synth.grid(s, 16, 16), 2, 40, 24), "SELECT CAST(1 AS BIGINT) AS within")
register("planted_cut_bound", known_cut(synth.planted, 8, 40, 420), "SELECT CAST(1 AS BIGINT) AS within")


def exact_nation12(spark: SparkSession, d: str) -> DataFrame:
    """(cut): the least cut of the first twelve nations into six and six, by enumeration of sides as rows."""
    e = F.broadcast(tables.nation_trade(spark, d).where("src < 12 and dst < 12"))
    sides = spark.range(1 << 11).withColumnRenamed("id", "s").where("bit_count(s) = 6")
    bit = lambda c: F.expr(f"shiftright(s, cast({c} as int)) & 1")
    cuts = sides.crossJoin(e).groupBy("s").agg(F.sum(F.when(bit("src") != bit("dst"), F.col("w")).otherwise(0)).alias("cut"))
    return cuts.agg(F.min("cut").alias("cut"))


register("exact_nation12_k2", exact_nation12, with_graph("nation_trade", "WITH s AS (SELECT range AS s FROM range(2048) WHERE bit_count(range) = 6) SELECT CAST(min(c) AS BIGINT) AS cut FROM (SELECT s, sum(CASE WHEN (s >> src) & 1 <> (s >> dst) & 1 THEN w ELSE 0 END) AS c FROM s, e WHERE src < 12 AND dst < 12 GROUP BY s)"))
register("exact_grid_3x4", lambda s, d: _exact_grid(s), "SELECT CAST(3 AS BIGINT) AS cut")


def _exact_grid(spark: SparkSession) -> DataFrame:
    from ..operators import local

    g = from_edges(synth.grid(spark, 3, 4))

    def run(group):
        import pyarrow as pa

        _, csr = partitioner.to_csr(group)
        return pa.table({"cut": pa.array([local.exact(csr, 2, 6)], pa.int64())})

    return partitioner.rows_of(g).withColumn("one", F.lit(1)).groupBy("one").applyInArrow(run, "cut long")


def bisect_facts(g: SplitGraph) -> DataFrame:
    """(assigned, blocks, over): one step of splitting every block, each in its task."""
    part, blocks = partitioner.bisect_blocks(g, g.nodes.select("id", F.lit(0).alias("block")), {0: 2}, 2, Options(tries=1, repeats=1), g.facts.weight)
    caps = partitioner.caps_of(g.nodes.sparkSession, blocks, g.facts.weight, 2, 0.03, g.facts.heaviest)
    return part.agg(F.count_distinct("id").alias("assigned"), F.count_distinct("block").alias("blocks")).crossJoin(supersteps.overload(g, part, caps).agg(F.count_if(F.col("over") > 0).alias("over")))


register("bisect_doc_lines", on("doc_lines", bisect_facts), with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS assigned, CAST(2 AS BIGINT) AS blocks, CAST(0 AS BIGINT) AS over"))


def finish_facts(g: SplitGraph) -> DataFrame:
    """(assigned, blocks): all remaining halvings of each block at once."""
    part, blocks = partitioner.bisect_blocks(g, g.nodes.select("id", (F.col("id") % 2).cast("int").alias("block")), {0: 3, 1: 4}, 7, Options(tries=1, repeats=1), g.facts.weight, stop=1)
    return part.agg(F.count_distinct("id").alias("assigned"), F.count_distinct("block").alias("blocks"))


register("finish_splits", on("user_next", finish_facts), with_graph("user_next", "SELECT (SELECT count(*) FROM v) AS assigned, CAST(7 AS BIGINT) AS blocks"))


def two_hop_star(spark: SparkSession, d: str) -> DataFrame:
    """(clusters): a star of 101 nodes whose hub's cluster is full is halved by two-hop merging alone."""
    g = from_edges(synth.star(spark, 101))
    state = g.nodes.select("id", "w", F.when(F.col("id") <= 2, F.lit(0)).otherwise(F.col("id")).cast("long").alias("label"), F.when(F.col("id") > 2, F.lit(0).cast("long")).alias("fav"))
    return supersteps.two_hop(state, 101, 3.0).agg(F.count_distinct("label").alias("clusters"))


register("two_hop_star", two_hop_star, "SELECT CAST(50 AS BIGINT) AS clusters")


# ---------------------------------------------------------------- statistics over a frame of runs

def runs_frame(spark: SparkSession, d: str) -> DataFrame:
    """A frame of runs made by arithmetic over ``lineitem``, so that any engine can make it."""
    li = table(spark, d, "lineitem")
    return li.select(
        F.concat(F.lit("a"), (F.col("l_linenumber") % 5).cast("string")).alias("algo"), F.concat(F.lit("g"), (F.col("l_suppkey") % 20).cast("string")).alias("graph"), (F.col("l_partkey") % 4 + 2).cast("int").alias("k"),
        (F.col("l_orderkey") % 3).cast("int").alias("seed"), F.pow(F.lit(4.0), (F.col("l_orderkey") % 3).cast("double")).cast("int").alias("p"), F.col("l_quantity").alias("secs"), (F.round(F.col("l_extendedprice")).cast("long") + 1).alias("cut"),
        (F.col("l_partkey") % 110).alias("max_block_w"), F.lit(100.0).alias("strict_cap"), F.when(F.col("l_quantity") > 48, "timeout").when(F.col("l_quantity") < 2, "crash").otherwise("ok").alias("status"),
        F.create_map(F.lit("coarsen"), F.col("l_quantity") * 0.5, F.lit("refine"), F.col("l_quantity") * 0.25 + F.col("l_tax")).alias("phase"),
    )


_RUNS = """r AS (SELECT 'a' || (l_linenumber % 5) AS algo, 'g' || (l_suppkey % 20) AS graph, CAST(l_partkey % 4 + 2 AS INTEGER) AS k, CAST(l_orderkey % 3 AS INTEGER) AS seed, CAST(pow(4, l_orderkey % 3) AS INTEGER) AS p,
l_quantity AS secs, CAST(round(l_extendedprice) AS BIGINT) + 1 AS cut, l_partkey % 110 AS max_block_w, 100.0::DOUBLE AS strict_cap, CASE WHEN l_quantity > 48 THEN 'timeout' WHEN l_quantity < 2 THEN 'crash' ELSE 'ok' END AS status,
l_quantity * 0.5::DOUBLE AS coarsen, l_quantity * 0.25::DOUBLE + l_tax AS refine FROM lineitem)"""
_SEEDS = "s AS (SELECT algo, graph, k, avg(secs) AS secs, avg(cut) AS cut, count(*) AS seeds FROM r GROUP BY ALL)"
_IMB = "(status = 'ok' AND max_block_w > strict_cap)"


def measured(name: str, fn: Callable[[DataFrame], DataFrame], sql: str, doubles: tuple[str, ...] = ()) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        out = fn(runs_frame(spark, d))
        return out.select(*[F.round(c, 6).alias(c) if c in doubles else F.col(c) for c in out.columns])

    rounded = f"SELECT * REPLACE ({', '.join(f'round({c}, 6) AS {c}' for c in doubles)}) FROM ({sql})" if doubles else sql
    register(name, run, f"WITH {_RUNS}, {_SEEDS} {rounded}")


measured("agg_seeds", stats.agg_seeds, "SELECT * FROM s", ("secs", "cut"))
measured("geo_mean_runs", lambda r: r.groupBy("algo").agg(stats.geo_mean("secs").alias("secs"), stats.geo_mean("cut").alias("cut")), "SELECT algo, exp(avg(ln(secs))) AS secs, exp(avg(ln(cut))) AS cut FROM r GROUP BY algo", ("secs", "cut"))
measured("harm_mean_speedup", lambda r: stats.speedup(r).groupBy("p").agg(stats.harm_mean("speedup").alias("speedup")), "SELECT p, count(*) / sum(1 / speedup) AS speedup FROM (SELECT a.p, b.t / a.t AS speedup FROM (SELECT graph, k, p, avg(secs) AS t FROM r GROUP BY ALL) a JOIN (SELECT graph, k, avg(secs) AS t FROM r WHERE p = 1 GROUP BY ALL) b USING (graph, k)) GROUP BY p", ("speedup",))
measured("performance_profile", lambda r: stats.performance_profile(stats.agg_seeds(r), [1.0, 1.1, 1.5, 2.0]), "SELECT algo, tau, avg(CASE WHEN cut <= tau * best THEN 1.0::DOUBLE ELSE 0 END) AS share FROM (SELECT *, min(cut) OVER (PARTITION BY graph, k) AS best FROM s), (VALUES (1.0::DOUBLE), (1.1), (1.5), (2.0)) t(tau) GROUP BY ALL", ("share",))
measured("profile_tau_grid", lambda r: r.select("algo").distinct().crossJoin(F.broadcast(r.sparkSession.createDataFrame([(1.0,), (1.1,), (1.5,), (2.0,)], "tau double"))), "SELECT algo, tau FROM (SELECT DISTINCT algo FROM r), (VALUES (1.0::DOUBLE), (1.1), (1.5), (2.0)) t(tau)")
measured("share_best", lambda r: stats.share_best(stats.agg_seeds(r)), "SELECT algo, avg(CASE WHEN cut <= best THEN 1.0::DOUBLE ELSE 0 END) AS share FROM (SELECT *, min(cut) OVER (PARTITION BY graph, k) AS best FROM s) GROUP BY algo", ("share",))
measured("at_least_twice", lambda r: stats.at_least_twice(stats.agg_seeds(r), "secs"), "SELECT algo, 1 - avg(CASE WHEN secs <= 2 * best THEN 1.0::DOUBLE ELSE 0 END) AS share FROM (SELECT *, min(secs) OVER (PARTITION BY graph, k) AS best FROM s) GROUP BY algo", ("share",))
measured("rolling_geo_mean", lambda r: stats.rolling_geo_mean(stats.agg_seeds(r), "seeds", "secs").select("algo", "graph", "k", "rolling"), "SELECT algo, graph, k, exp(avg(ln(secs)) OVER (PARTITION BY algo ORDER BY seeds, graph, k ROWS BETWEEN 49 PRECEDING AND CURRENT ROW)) AS rolling FROM s", ("rolling",))
measured("outcome_counts", stats.outcome_counts, f"SELECT algo, count(*) FILTER (status = 'timeout') AS timeouts, count(*) FILTER (status = 'crash') AS crashes, count(*) FILTER {_IMB} AS imbalanced, count(*) FILTER (status = 'ok' AND NOT {_IMB}) AS feasible FROM r GROUP BY algo")
measured("infeasible_marks", stats.mark_infeasible, f"SELECT algo, graph, k, bool_and(status <> 'ok' OR {_IMB}) AS infeasible FROM r GROUP BY ALL")
measured("time_limit_fill", lambda r: stats.with_time_limit(r, 30.0).groupBy("algo").agg(F.avg("secs").alias("secs")), "SELECT algo, avg(CASE WHEN status = 'timeout' THEN 30 ELSE least(secs, 30) END) AS secs FROM r GROUP BY algo", ("secs",))
_REL = "SELECT a.algo, exp(avg(ln(greatest(a.{v} * {f}, 1) / greatest(b.{v} * {f}, 1)))) AS relative FROM (SELECT algo, graph, k, avg({v}) AS {v} FROM r WHERE {c} GROUP BY ALL) a JOIN (SELECT graph, k, avg({v}) AS {v} FROM r WHERE {c} AND algo = 'a1' GROUP BY ALL) b USING (graph, k) GROUP BY a.algo"
measured("relative_time", lambda r: stats.relative_time(r, "a1"), _REL.format(v="secs", f="1e6", c="status <> 'crash'"), ("relative",))
measured("relative_cut", lambda r: stats.relative_cut(r, "a1"), _REL.format(v="cut", f="1", c="status = 'ok'"), ("relative",))
measured("speedup_by_phase", stats.speedup_by_phase, "SELECT phase, p, count(*) / sum(t / t1) AS speedup FROM (SELECT graph, k, p, phase, avg(t) AS t FROM r, LATERAL (VALUES ('coarsen', coarsen), ('refine', refine)) x(phase, t) GROUP BY ALL) a JOIN (SELECT graph, k, phase, avg(t) AS t1 FROM r, LATERAL (VALUES ('coarsen', coarsen), ('refine', refine)) x(phase, t) WHERE p = 1 GROUP BY ALL) b USING (graph, k, phase) GROUP BY phase, p", ("speedup",))
measured("cumulative_speedup", lambda r: stats.cumulative_speedup(stats.speedup(r)), "SELECT p, t1, count(*) OVER w / sum(1 / speedup) OVER w AS cumulative FROM (SELECT a.p, b.t AS t1, b.t / a.t AS speedup FROM (SELECT graph, k, p, avg(secs) AS t FROM r GROUP BY ALL) a JOIN (SELECT graph, k, avg(secs) AS t FROM r WHERE p = 1 GROUP BY ALL) b USING (graph, k)) WINDOW w AS (PARTITION BY p ORDER BY t1 DESC RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)", ("t1", "cumulative"))
measured("imbalance_percentiles", stats.imbalance_percentiles, f"SELECT algo, quantile_cont(max_block_w / strict_cap, 0.5) AS median, max(max_block_w / strict_cap) AS most FROM r WHERE {_IMB} GROUP BY algo", ("median", "most"))
measured("cut_rollup", lambda r: r.rollup("algo", "graph").agg(F.sum("cut").alias("cut")), "SELECT algo, graph, CAST(sum(cut) AS BIGINT) AS cut FROM r GROUP BY ROLLUP (algo, graph)")
measured("cut_cube", lambda r: r.cube("algo", "k").agg(F.sum("cut").alias("cut")).select("algo", F.coalesce("k", F.lit(-1)).alias("k"), "cut"), "SELECT algo, coalesce(k, -1) AS k, CAST(sum(cut) AS BIGINT) AS cut FROM r GROUP BY CUBE (algo, k)")
measured("cut_grouping_sets", lambda r: r.groupingSets([[F.col("algo")], [F.col("graph"), F.col("k")]], "algo", "graph", "k").agg(F.sum("cut").alias("cut")).select("algo", "graph", F.coalesce("k", F.lit(-1)).alias("k"), "cut"), "SELECT algo, graph, coalesce(k, -1) AS k, CAST(sum(cut) AS BIGINT) AS cut FROM r GROUP BY GROUPING SETS ((algo), (graph, k))")
measured("phase_map_explode", lambda r: r.select("algo", F.explode("phase").alias("name", "t")).groupBy("algo", "name").agg(F.sum("t").alias("t")), "SELECT algo, name, sum(t) AS t FROM r, LATERAL (VALUES ('coarsen', coarsen), ('refine', refine)) x(name, t) GROUP BY ALL", ("t",))
measured("runs_union", lambda r: r.where("algo = 'a1'").select("graph", "cut").unionByName(r.where("algo = 'a2'").select("graph", "cut")).groupBy("graph").agg(F.max("cut").alias("cut")), "SELECT graph, max(cut) AS cut FROM r WHERE algo IN ('a1', 'a2') GROUP BY graph")

# ---------------------------------------------------------------- reports

register("top_blocks", on("copurchase", lambda g: measures.block_weights(g, _mod(g, "copurchase", 50)).orderBy(F.desc("w"), "block").limit(5)), with_graph("copurchase", "SELECT CAST(id % 50 AS INTEGER) AS block, count(*) AS w, count(*) AS n FROM v GROUP BY 1 ORDER BY w DESC, block LIMIT 5"))
register("topk_boundary", on("user_next", lambda g: measures.both_blocks(g.edges, _mod(g, "user_next")).where("bs <> bd").groupBy(F.col("bs").alias("block"), F.col("src").alias("id")).agg(F.sum("w").alias("outward")).withColumn("r", F.row_number().over(W.partitionBy("block").orderBy(F.desc("outward"), "id"))).where("r <= 3")), with_graph("user_next", "SELECT * FROM (SELECT CAST(src % 4 AS INTEGER) AS block, src AS id, CAST(sum(w) AS BIGINT) AS outward, CAST(row_number() OVER (PARTITION BY src % 4 ORDER BY sum(w) DESC, src) AS INTEGER) AS r FROM d WHERE src % 4 <> dst % 4 GROUP BY src) WHERE r <= 3"))
register("scan_lineitem_edges", lambda s, d: table(s, d, "lineitem").where("l_quantity >= 49").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n")), "SELECT l_suppkey, count(*) AS n FROM lineitem WHERE l_quantity >= 49 GROUP BY 1")
register("dangling_edges", lambda s, d: table(s, d, "lineitem").select("l_orderkey").join(table(s, d, "orders").where("o_orderkey % 10 <> 0").select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_anti").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n")), "SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE o_orderkey % 10 <> 0) GROUP BY 1")
register("vec_cosine", lambda s, d: _cosines(s, d), "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")


def _cosines(spark: SparkSession, d: str) -> DataFrame:
    v = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, t: s + t)
    x, y = v.select(F.col("vec_id").alias("a"), F.col("e").alias("x")), v.select(F.col("vec_id").alias("b"), F.col("e").alias("y"))
    return x.join(y, F.col("b") == F.col("a") + 1).select("a", "b", F.round(dot(F.col("x"), F.col("y")) / F.sqrt(dot(F.col("x"), F.col("x")) * dot(F.col("y"), F.col("y"))), 6).alias("cosine"))


# ---------------------------------------------------------------- small pieces that steps are made of

register("labels_changed", on("user_next", lambda g: _changed(g)), with_graph("user_next", "SELECT id FROM v WHERE id % 4 <> id % 3"))
register("drop_loops", lambda s, d: table(s, d, "lineitem").select((F.col("l_partkey") % 50).alias("a"), (F.col("l_suppkey") % 50).alias("b")).where("a <> b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("w")), "SELECT l_partkey % 50 AS a, l_suppkey % 50 AS b, count(*) AS w FROM lineitem WHERE l_partkey % 50 <> l_suppkey % 50 GROUP BY 1, 2")
register("boundary_exists", on("user_next", lambda g: g.nodes.join(g.edges.where("src % 4 <> dst % 4").select(F.col("src").alias("id")), "id", "left_semi").agg(F.count(F.lit(1)).alias("n"))), with_graph("user_next", "SELECT count(*) AS n FROM v WHERE EXISTS (SELECT 1 FROM d WHERE d.src = v.id AND d.src % 4 <> d.dst % 4)"))
register("block_rank", on("copurchase", lambda g: measures.block_weights(g, _mod(g, "copurchase", 9)).select("block", F.rank().over(W.orderBy(F.desc("w"))).alias("r"), F.dense_rank().over(W.orderBy(F.desc("w"))).alias("dr"), F.ntile(3).over(W.orderBy(F.desc("w"), "block")).alias("third"))), with_graph("copurchase", "SELECT CAST(b AS INTEGER) AS block, CAST(rank() OVER (ORDER BY n DESC) AS INTEGER) AS r, CAST(dense_rank() OVER (ORDER BY n DESC) AS INTEGER) AS dr, CAST(ntile(3) OVER (ORDER BY n DESC, b) AS INTEGER) AS third FROM (SELECT id % 9 AS b, count(*) AS n FROM v GROUP BY 1)"))


def _changed(g: SplitGraph) -> DataFrame:
    one, two = g.nodes.select("id", (F.col("id") % 4).alias("a")), g.nodes.select("id", (F.col("id") % 3).alias("b"))
    return one.join(two, "id").where(~F.col("a").eqNullSafe(F.col("b"))).select("id")


def relative_gains(g: SplitGraph) -> DataFrame:
    """(id, d, key): best cut reduction of each node of block 0 toward any other of four blocks, weighed by node weight."""
    part = _mod(g, "user_next").withColumn("label", F.col("block").cast("long"))
    rated = supersteps.ratings(g.edges, part).join(part.select("id", F.col("label").alias("mine")), "id").where("mine = 0")
    best = rated.groupBy("id").agg(F.coalesce(F.max(F.when(F.col("label") != 0, F.col("rate"))), F.lit(0)).alias("out"), F.coalesce(F.max(F.when(F.col("label") == 0, F.col("rate"))), F.lit(0)).alias("inner"))
    d = (F.col("out") - F.col("inner")).cast("double")
    return best.select("id", d.alias("d"), F.round(rules.relative_gain(d, F.col("id") % 7 + 1), 6).alias("key"))


register("relative_gains", on("user_next", relative_gains), with_graph("user_next", """WITH r AS (SELECT dst AS id, src % 4 AS label, sum(w) AS rate FROM d WHERE dst % 4 = 0 GROUP BY 1, 2), b AS (SELECT id, (coalesce(max(rate) FILTER (label <> 0), 0) - coalesce(max(rate) FILTER (label = 0), 0))::DOUBLE AS d FROM r GROUP BY id)
SELECT id, d, round(CASE WHEN d >= 0 THEN d * (id % 7 + 1) ELSE d / (id % 7 + 1) END, 6) AS key FROM b"""))


def large_k_outcomes(spark: SparkSession, d: str) -> DataFrame:
    """(algo, ours_feasible): on many blocks of few nodes, our scheme is feasible on every instance."""
    from . import workloads

    runs = workloads.run_grid(spark, d, ["user_next"], (16, 64), ["one_cycle"], options={"c": 100, "tries": 1, "repeats": 1})
    return runs.groupBy("algo").agg(F.bool_and((F.col("status") == "ok") & (F.col("cut") >= 0)).alias("finished"), F.count(F.lit(1)).alias("runs"))


register("large_k_outcomes", large_k_outcomes, "SELECT 'one_cycle' AS algo, TRUE AS finished, CAST(2 AS BIGINT) AS runs")
register("nodes_by_bucket", on("user_next", lambda g: supersteps.rearranged(g)[1].groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("new").alias("low"), F.max("new").alias("high"))), with_graph("user_next", """WITH b AS (SELECT src AS id, CAST(floor(log2(count(*))) AS INTEGER) AS bucket FROM d GROUP BY 1), r AS (SELECT bucket, row_number() OVER (ORDER BY bucket, id) - 1 AS new FROM b) SELECT bucket, count(*) AS n, min(new) AS low, max(new) AS high FROM r GROUP BY bucket"""))
register("cost_log", on("user_next", lambda g: partitioner.cost_log(g, 4, Options(c=60, rounds=1, classes=1)).agg(F.max("level").alias("deepest"), F.bool_and(F.col("n") <= F.col("n_before")).alias("shrinks")).select((F.col("deepest") >= 1).alias("several"), "shrinks")), "SELECT TRUE AS several, TRUE AS shrinks")
register("bisect_oversize", on("doc_lines", lambda g: _oversize(g)), with_graph("doc_lines", "SELECT (SELECT count(*) FROM v) AS assigned, CAST(2 AS BIGINT) AS blocks, CAST(0 AS BIGINT) AS over"))


def _oversize(g: SplitGraph) -> DataFrame:
    part = partitioner.bisect_distributed(g, 1, 1, 0.03, seed=0)
    caps = partitioner.caps_of(g.nodes.sparkSession, {0: 1, 1: 1}, g.facts.weight, 2, 0.03, g.facts.heaviest)
    return part.agg(F.count_distinct("id").alias("assigned"), F.count_distinct("block").alias("blocks")).crossJoin(supersteps.overload(g, part, caps).agg(F.count_if(F.col("over") > 0).alias("over")))
