"""Registered queries against their SQL, a part of them here; the rest is compared by the driver."""

import pytest

from graphsummary.operators import rounds
from graphsummary.plans import oracles, queries, workloads
from tests.compare import same

NAMES = ["canonical_edges", "degree_histogram", "base_cap_mode", "event_pointers", "assignment_le_source", "assignment_two_rounds", "bulk_assignment", "sketch_estimate_d4", "sketch_column_min", "superedges", "modularity_weighted",
         "intra_probability", "nmi", "colour_bands", "move_step", "components", "edges_sessions", "edges_sliding", "shared_line_edges", "sizes_grouping_sets", "top_neighbours"]


def test_every_oracle_has_a_query():
    assert set(oracles.ORACLES) <= set(queries.QUERIES) and set(workloads.ORACLES) <= set(workloads.QUERIES)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf, name):
    assert same(queries.QUERIES[name](spark, sf), oracles.ORACLES[name], sf)


@pytest.mark.parametrize("name", ["w4_cap_scale", "w9_extent_first_step", "w12_overhead", "time_saved", "w17_modularity_truths"])
def test_workload(spark, sf, name):
    assert same(workloads.QUERIES[name](spark, sf), workloads.ORACLES[name], sf)


def test_community_members_all(spark, sf):
    assert same(queries.QUERIES["community_members_all"](spark, sf), oracles.ORACLES["community_members_all"], sf)
    listed = [x for r in queries.QUERIES["community_members_all"](spark, sf).collect() for x in r["members"].split(",")]
    assert len(listed) == len(set(listed)) == queries.QUERIES["degrees"](spark, sf).count()


def test_frequent_and_short_lines_link_documents(spark, sf, tmp_path):
    assert same(queries.QUERIES["shared_line_hubs"](spark, sf), oracles.ORACLES["shared_line_hubs"], sf)
    rows = [(i, f"a line that stands in very many documents\nown {i}") for i in range(60)] + [(100, "short\nx"), (101, "y\n short ")]
    spark.createDataFrame(rows, "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {tuple(r) for r in queries.QUERIES["shared_line_hubs"](spark, str(tmp_path)).collect()}
    assert got == {(0, i) for i in range(1, 60)} | {(100, 101)}


def test_general_operators_on_the_whole_graph(spark, sf):
    pairs = "select distinct o_custkey as src, l_partkey + 10000000 as dst from orders join lineitem on o_orderkey = l_orderkey"
    degrees = f"with e as ({pairs}) select node, count(*) as deg from (select src as node from e union all select dst from e) group by node"
    assert same(queries.QUERIES["degrees_cust_part"](spark, sf), degrees, sf)
    assert same(queries.QUERIES["degrees"](spark, sf), oracles.ORACLES["degrees"], sf)


def test_independent_runs_and_rounds_of_one_run_agree(spark, sf):
    e = workloads._edges(spark, sf, "planted")
    nested = {m["round"]: m for m in rounds.detect(e, 4, stop_when_stable=False, with_q=True).metrics}
    own = {r["rounds"]: r for r in workloads.w3_independent(spark, sf).collect()}
    assert set(own) == {2, 3, 4}
    for k, r in own.items():
        assert (r["sn"], r["se"]) == (nested[k]["sn"], nested[k]["se"]) and abs(r["q"] - nested[k]["q"]) < 1e-9


def test_inner_and_cross_edges_of_every_round(spark, sf):
    got = {(r["setting"], r["metric"]): r["value"] for r in workloads.w8(spark, sf, 3).collect()}
    e = workloads._edges(spark, sf, "planted")
    rows = [(r["src"], r["dst"]) for r in e.collect()]
    for k in (1, 3):
        label = {r["node"]: r["community"] for r in rounds.detect(e, k, stop_when_stable=False).assignment.collect()}
        inner = sum(label[a] == label[b] for a, b in rows)
        assert (got[str(k), "inner"], got[str(k), "cross"]) == (inner, len(rows) - inner)
