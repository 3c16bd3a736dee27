"""Steps whose rows no single task may hold, on small fixtures: running sums, quotas, hubs, oversize blocks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphsplit.model import SplitGraph, from_edges
from graphsplit.operators import supersteps
from graphsplit.operators.local import Options
from graphsplit.plans import measures, partitioner
from graphsplit.sources import synth
from graphsplit.storage import spill


@pytest.mark.parametrize("by", [(), ("g",)])
def test_running_weight_covers_each_unit_of_weight_once(spark, by):
    rows = spark.range(500).select("id", (F.col("id") % 5 + 1).alias("w"), (F.col("id") % 3 % 2).alias("g"))
    got = supersteps.running_weight(rows, by, slices=7).toPandas()
    for _, part in got.groupby("g") if by else [(0, got)]:
        part = part.sort_values("upto")
        assert part["upto"].tolist() == np.cumsum(part["w"]).tolist()
    assert len(got) == 500
    assert supersteps.running_weight(rows.limit(0), by).count() == 0


def test_first_by_hash_is_a_sorted_limit(spark):
    from graphsplit.functions.hashing import mix

    rows = spark.range(3000).withColumn("into", F.expr("id div 2"))
    for quota in (1, 777, 2999, 3000, 9000):
        got = {r.id for r in supersteps.first_by_hash(rows, "into", quota, 3).collect()}
        assert got == {r.id for r in rows.orderBy(mix("into", 3), "id").limit(quota).collect()}


def test_two_hop_pairs_a_hub_in_parts(spark, monkeypatch):
    monkeypatch.setattr(supersteps, "PAIRED_AT_ONCE", 10)
    g = from_edges(synth.star(spark, 101))
    state = g.nodes.select("id", "w", F.col("id").alias("label"), F.when(F.col("id") > 0, F.lit(0).cast("long")).alias("fav"))
    out = supersteps.two_hop(state, 101, 2.0).toPandas()
    assert out.groupby("label")["w"].sum().max() == 2 and 50 <= out["label"].nunique() <= 50 + 11


@pytest.mark.parametrize("heavy", [1, 30])
def test_fill_empties_one_full_block_into_many(spark, heavy):
    nodes = spark.range(400).select("id", F.when(F.col("id") == 7, heavy).otherwise(1).cast("long").alias("w"))
    g = SplitGraph(nodes, from_edges(synth.ring(spark, 400)).edges)
    caps = partitioner.caps_of(spark, {b: 1 for b in range(16)}, g.facts.weight, 16, 0.03, g.facts.heaviest)
    part = supersteps.fill(g, nodes.select("id", F.lit(3).alias("block")), caps)
    assert supersteps.overload(g, part, caps).where("over > 0").count() == 0
    assert part.select("id").distinct().count() == part.count() == 400


def test_blocks_that_no_task_can_take_are_split_as_frames(spark):
    g = from_edges(synth.planted(spark))
    g = SplitGraph(spill(g.nodes, "nodes"), spill(g.edges, "edges"))
    one, o = g.nodes.select("id", F.lit(0).alias("block")), Options(c=150, tries=1, repeats=1)
    part, blocks = partitioner.bisect_blocks(g, one, {0: 7}, 7, o, g.facts.weight, stop=1, task_edges=2500)
    assert sorted(blocks) == list(range(7)) and set(blocks.values()) == {1}
    assert part.select("id").distinct().count() == part.count() == 400
    caps = partitioner.caps_of(spark, blocks, g.facts.weight, 7, 0.2, 1)
    assert supersteps.overload(g, part, caps).where("over > 0 or held = 0").count() == 0
    cut, trivial = (measures.edge_cut(g, p).first()[0] for p in (part, partitioner.mod_cut(g.nodes, 7)))
    assert cut < trivial


def test_only_blocks_beyond_the_limit_are_large(spark):
    g = from_edges(synth.cliques(spark, 2, 20))
    part = g.nodes.select("id", F.when(F.col("id") < 20, 0).when(F.col("id") < 25, 1).otherwise(2).alias("block"))
    assert partitioner.large_blocks(g, part, {0: 2, 1: 2, 2: 1}, 200) == [0]
    assert partitioner.large_blocks(g, part, {0: 2, 1: 2, 2: 1}, 10_000) == []


def test_new_nodes_of_any_weight_get_a_block_or_null(spark):
    from graphsplit.streaming.interactions import place_new_nodes

    new = spark.range(10, 60).select("id", (F.col("id") % 4 + 1).alias("w"))
    none = spark.createDataFrame([], "src long, dst long, w long")
    caps = spark.createDataFrame([(b, 40.0, 3) for b in range(4)], "block int, cap double, held long")
    got = place_new_nodes(new, none, spark.createDataFrame([], "id long, block int"), caps).join(new, "id").toPandas()
    assert sorted(got["id"]) == list(range(10, 60))
    assert (got.dropna().groupby("block")["w"].sum() <= 37).all() and len(got.dropna()) >= 45
    full = spark.createDataFrame([(0, 3.0, 3)], "block int, cap double, held long")
    assert place_new_nodes(new, none, spark.createDataFrame([], "id long, block int"), full).where("block is null").count() == 50


def test_whole_builders_keep_what_many_share(spark, tmp_path):
    from graphsplit.sources import tables

    line = "a line that all documents share"
    spark.createDataFrame([(i, f"{line}\nonly document {i} has this line\nshared by two documents, pair {i // 2}") for i in range(60)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, f'<a href="/all"><a href="/p{i}"><a href="/all">') for i in range(60)], "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    assert tables.page_links(spark, str(tmp_path)).count() == 0
    assert {tuple(r) for r in tables.page_links(spark, str(tmp_path), None).collect()} == {(i, "all", 2) for i in range(60)}
    pairs = {(r.src, r.dst, r.w) for r in tables.doc_lines_whole(spark, str(tmp_path)).collect()}
    star = {dst for _, dst, _ in pairs if dst % 2} | {src for src, _, _ in pairs if src % 2}
    assert len(star) == 1 and len(pairs) == 90
    hub = star.pop()
    assert pairs == {(min(2 * i, hub), max(2 * i, hub), 1) for i in range(60)} | {(4 * i, 4 * i + 2, 1) for i in range(30)}


def test_coordinate_header_in_a_small_file(spark, tmp_path):
    from graphsplit.sources import files

    (tmp_path / "a.txt").write_text("% a comment\n900 900 899\n")
    (tmp_path / "b.txt").write_text("".join(f"{i} {i + 1} 2\n" for i in range(1, 700)))
    (tmp_path / "c.txt").write_text("".join(f"{i} {i + 1}\n" for i in range(700, 900)))
    got = {(r.src, r.dst): r.w for r in files.read_coordinate(spark, str(tmp_path)).collect()}
    assert got == {(i - 1, i): 2 if i < 700 else 1 for i in range(1, 900)}
    (tmp_path / "c.txt").unlink()
    with pytest.raises(ValueError):
        files.read_coordinate(spark, str(tmp_path))


def test_batches_have_a_time_limit_and_a_size_limit(spark):
    g = from_edges(synth.planted(spark))
    with pytest.raises(ValueError):
        partitioner.run_many(g, [{"k": 2}], task_edges=100)
    runs = partitioner.run_many(g, [{"k": 8, "c": 50, "tries": 1, "repeats": 1}, {"k": 64, "c": 10, "tries": 40, "repeats": 40}, {"k": 8, "c": 50, "tries": 1, "repeats": 1, "cores": 4}], limit=6.0)
    found = {r.inst: (r.status, r.n) for r in runs.groupBy("inst").agg(F.max("status").alias("status"), F.count("id").alias("n")).collect()}
    assert found == {0: ("ok", 400), 1: ("timeout", 0), 2: ("ok", 400)}
    # With four cores no graph here has more than 2 * 4 * 50 nodes, so all splits and refinement count as the bottom.
    phases = {r.inst: set(r.phase) for r in runs.where("id is null and inst <> 1").collect()}
    assert "initial" in phases[0] and phases[2] == {"total", "coarsening", "bottom"}


def test_in_order_counts_what_comes_earlier(spark):
    rows = spark.range(1000).withColumn("w", F.lit(2).cast("long")).withColumn("k", F.lit(7))
    out = supersteps.in_order(rows, [F.desc("k"), F.col("id")]).toPandas()
    assert (out["before"] == 2 * out["id"]).all()
    assert supersteps.in_order(rows.where("id < 0"), [F.col("id")]).count() == 0


def test_nodes_without_edges_pair_up(spark):
    state = spark.range(10).select("id", F.lit(1).cast("long").alias("w"), F.col("id").alias("label"), F.lit(None).cast("long").alias("fav"))
    edges = spark.createDataFrame([(0, 1, 1), (1, 0, 1)], "src long, dst long, w long")
    out = supersteps.two_hop(state, 10, 2.0, edges).toPandas()
    assert out["label"].nunique() == 6 and set(out.loc[out["id"] < 2, "label"]) == {0, 1}


def test_store_of_another_graph_is_refused(spark, tmp_path):
    g, o = from_edges(synth.grid(spark, 6, 6)), Options(c=10, rounds=1, classes=1, tries=1, repeats=1)
    levels, bottom = partitioner.descend(g, 2, o, 10, str(tmp_path))
    again, same = partitioner.descend(g, 2, o, 10, str(tmp_path))
    assert partitioner.kept_level(spark, str(tmp_path), 0) is not None
    assert len(again) == len(levels) and same.facts == bottom.facts
    with pytest.raises(ValueError):
        partitioner.descend(from_edges(synth.grid(spark, 6, 5)), 2, o, 10, str(tmp_path))
    with pytest.raises(ValueError):
        partitioner.descend(g, 3, o, 10, str(tmp_path))


def test_a_heavy_level_does_not_pass(spark):
    g = from_edges(synth.grid(spark, 4, 4))
    one = g.nodes.select("id", F.lit(0).alias("block"))
    with pytest.raises(AssertionError):
        partitioner.assure_level(g, one, {0: 1, 1: 1}, 2, Options(), 16, 2)
    with pytest.raises(AssertionError):
        partitioner.assure_level(g, one, {0: 2}, 2, Options(), 16, 2)


def test_matched_labels_move_least(spark):
    nodes = spark.range(60).withColumn("w", F.lit(1).cast("long"))
    old = nodes.select("id", (F.col("id") % 3).cast("int").alias("block"))
    new = nodes.select("id", F.when(F.col("id") < 6, 3).otherwise((F.col("id") + 1) % 3).cast("int").alias("block"))
    out = measures.match_labels(nodes, old, new).join(old.withColumnRenamed("block", "old"), "id").toPandas()
    assert (out["block"] != out["old"]).sum() == 6 and out["block"].nunique() == 4


def test_joins_follow_their_hints(spark, tmp_path):
    from graphsplit.sources import files

    g = from_edges(synth.grid(spark, 12, 12))
    part = partitioner.mod_cut(g.nodes, 4)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan(measures.edge_cut(g, part, "merge"))
    assert "ShuffledHashJoin" in plan(measures.edge_cut(g, part, "shuffle_hash"))
    edges, blocks = files.write_bucketed(g, part, "bucketed_test", str(tmp_path), 4)
    joined = edges.join(blocks.hint("merge"), edges["src"] == blocks["id"])
    assert "SortMergeJoin" in plan(joined) and "Exchange" not in plan(joined)
    assert measures.edge_cut(SplitGraph(g.nodes, edges), blocks, "merge").first() == measures.edge_cut(g, part).first()
    for name in ("bucketed_test_edges", "bucketed_test_blocks"):
        spark.sql(f"DROP TABLE {name}")


def test_a_packed_graph_comes_back_whole(spark, monkeypatch):
    monkeypatch.setattr(partitioner, "PACK", 50)
    nodes = spark.range(402).select((F.col("id") * 3 + (1 << 40)).alias("id"), (F.col("id") % 5 + 1).alias("w"))
    edges = synth.planted(spark).select((F.col("src") * 3 + (1 << 40)).alias("src"), (F.col("dst") * 3 + (1 << 40)).alias("dst"), (F.col("src") + F.col("dst") + 1).alias("w"))
    g = from_edges(edges, nodes=nodes, node_w="w")
    table = partitioner.packed(g).toArrow()
    ids, csr = partitioner.unpack(table)
    plain, own = partitioner.to_csr(partitioner.rows_of(g).toArrow())
    assert (ids == plain).all() and all((getattr(csr, x) == getattr(own, x)).all() for x in ("nw", "ptr", "src", "dst", "w"))


def test_graphs_beyond_two_million_edges_run_side_by_side_in_tasks(spark, monkeypatch):
    from graphsplit.model import Facts

    monkeypatch.setattr(partitioner, "partition_wide", lambda *_: pytest.fail("one instance after the other"))
    g = from_edges(synth.grid(spark, 8, 8))
    g._facts = Facts(64, 7_800_000, 64, 1, 7_800_000)
    assert partitioner.partition_many(g, [{"k": k, "c": 10} for k in (2, 4)]).groupBy("inst").count().collect() is not None


def test_batches_of_any_size_take_the_same_steps(spark, monkeypatch):
    from graphsplit.model import Facts

    monkeypatch.setattr(partitioner, "partition_wide", lambda *_: pytest.fail("other steps for a larger graph"))
    g = from_edges(synth.grid(spark, 8, 8))
    specs = [{"scheme": s, "k": 4, "c": 10, "tries": 1, "repeats": 1} for s in ("kway_fm", "direct_kway", "single_level_lp")]
    found = sorted(partitioner.partition_many(g, specs).collect())
    g._facts = Facts(64, 70_000_000, 64, 1, 70_000_000)
    assert sorted(partitioner.partition_many(g, specs).collect()) == found and len(found) == 3 * 64


@pytest.mark.parametrize("name", ["supp_part", "cust_part", "copurchase", "order_chain", "doc_lines", "nation_trade"])
@pytest.mark.parametrize("node_w", [None, "degree"])
def test_graphs_loaded_once_are_those_loaded(spark, name, node_w):
    from graphsplit.sources import tables

    d = "/root/testdata/sf0.001"
    one, two = tables.load_once(spark, d, name, node_w), tables.load(spark, d, name, node_w)
    assert one.edges.schema.simpleString() == two.edges.schema.simpleString() and one.nodes.schema.simpleString() == two.nodes.schema.simpleString()
    assert sorted(one.edges.collect()) == sorted(two.edges.collect()) and sorted(one.nodes.collect()) == sorted(two.nodes.collect())


@pytest.mark.parametrize("keys", [[(1, 1), (1, 1), (2, 1), (None, 1)], [(0, 0), (-1, -1), (-1, 0), (0, -1), (0, -1)]])
def test_two_sided_pairs_are_summed_once(spark, keys):
    from graphsplit.sources import tables

    pairs = tables.bipartite(spark.createDataFrame(keys, "l long, r long"), "l", "r")
    assert pairs._jdf.queryExecution().optimizedPlan().toString().count("Aggregate") == 1
    want = {}
    for a, b in keys:
        if a is not None:
            pair = (min(2 * a, 2 * b + 1), max(2 * a, 2 * b + 1))
            want[pair] = want.get(pair, 0) + 1
    assert {(r.src, r.dst): r.w for r in pairs.collect()} == want and pairs.count() == len(want)


def test_loading_once_sums_pairs_once(spark, monkeypatch):
    from graphsplit import model
    from graphsplit.sources import tables

    asked = []
    monkeypatch.setattr(model, "canonical", lambda *_, **__: asked.append(1) or pytest.fail("pairs summed again"))
    assert tables.load_once(spark, "/root/testdata/sf0.001", "supp_part").facts.m > 0 and not asked


def test_large_k_runs_build_their_graph_once(spark, monkeypatch):
    from graphsplit.plans import workloads
    from graphsplit.sources import tables

    asked, build = [], tables.GRAPHS["doc_lines"]
    monkeypatch.setitem(tables.GRAPHS, "doc_lines", lambda *x: asked.append(1) or build(*x))
    runs = workloads.run_large_k(spark, "/root/testdata/sf0.001", ("doc_lines",), ("one_cycle", "single_level_lp"), 1, {"c": 100, "tries": 1, "repeats": 1})
    assert len(asked) == 1 and {r.algo for r in runs.collect()} == {"one_cycle", "single_level_lp"}


def test_lines_are_shuffled_without_their_text(spark):
    from graphsplit.sources import tables

    pairs = tables.doc_lines(spark, "/root/testdata/sf0.001")
    assert "split(" not in pairs._jdf.queryExecution().optimizedPlan().toString()
    assert {f.dataType.typeName() for f in tables._named_lines(spark, "/root/testdata/sf0.001").schema} == {"long", "binary"}


def test_instances_get_partitions_of_their_own(spark):
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    got = partitioner.lanes_of(spark, 2 * parts).repartition(parts, "lane").groupBy(F.spark_partition_id().alias("p")).count().collect()
    assert sorted(r["count"] for r in got) == [2] * parts


def test_certificates_of_many_equal_those_of_one(spark):
    g = from_edges(synth.planted(spark))
    parts = partitioner.mod_cut(g.nodes, 3).withColumn("inst", F.lit(0)).unionByName(partitioner.hash_cut(g.nodes, 5).withColumn("inst", F.lit(2)))
    found = {r.k: r for r in measures.certify_many(g, parts, [{"k": 3}, {"k": 4}, {"k": 5}]).collect()}
    assert set(found) == {3, 5}
    for k, part in ((3, partitioner.mod_cut(g.nodes, 3)), (5, partitioner.hash_cut(g.nodes, 5))):
        assert found[k].cut == measures.edge_cut(g, part).first()[0] and found[k].mod_cut == measures.edge_cut(g, partitioner.mod_cut(g.nodes, k)).first()[0]
        assert found[k].edge_weight == g.facts.edge_weight
