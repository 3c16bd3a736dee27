"""Queries against their SQL on the smallest tables, plans of the wide steps, and model checks."""

import duckdb
import pytest

import __spark_entry__ as entry
from graphsplit.model import faults, from_edges
from graphsplit.operators import supersteps
from graphsplit.sources import synth, tables

DIR = "/root/testdata/sf0.001"
NAMES = """build_cust_part build_user_next build_doc_lines gen_planted gen_geometric formula_limits eps_table cluster_cap_table split_counts describe_user_next
edge_cut_copurchase_mod4 quotient_graph lp_ratings lp_round1_best lp_two_rounds strict_admission sampled_admission two_hop_pairs contract_mod overload_prefix
match_round1 weight_fill_cut snake_cut performance_profile cumulative_speedup cut_cube exact_grid_3x4 roundtrip_adjacency udf_formula_check stream_tumbling
stream_late stream_late_counted rerun_matched cogroup_inner observed_contraction bucketed_cut range_cut nodes_by_bucket""".split()


def rows(df):
    df = df[sorted(df.columns)]
    return sorted(map(str, df.astype(object).where(df.notna(), None).itertuples(index=False, name=None)))


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    assert rows(entry.queries()[name](spark, DIR).toPandas()) == rows(duck.execute(entry.oracle_sql()[name]).df())


def test_every_oracle_has_a_query():
    assert entry.oracle_sql().keys() <= entry.queries().keys()


def test_entry_runs(spark):
    out = entry.entry(spark).toPandas()
    assert len(out) == 8 and out["n"].sum() == 200


def test_graph_is_valid(spark):
    g = from_edges(synth.planted(spark))
    assert {r["check"]: r["rows"] for r in faults(g).collect()} == {c: 0 for c in ("node null or light", "node twice", "edge null or light", "loop", "pair twice", "one way only", "end is no node")}
    assert (g.facts.n, g.facts.m, g.facts.edge_weight) == (400, 2496, 2752)


def test_no_wide_step_runs_python_or_a_cartesian_product(spark):
    g = tables.load(spark, DIR, "copurchase")
    start = g.nodes.select("id", "w", g.nodes["id"].alias("label"))
    plan = supersteps.propose(g.edges, start, 5.0, 0)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("Python", "Pandas", "Arrow", "CartesianProduct", "BroadcastNestedLoopJoin"))


def test_pruned_scan(spark):
    plan = tables.supp_part(spark, DIR)._jdf.queryExecution().executedPlan().toString()
    assert "l_extendedprice" not in plan
