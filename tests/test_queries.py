"""Queries against their SQL on the smallest tables: all relational ones, and a selection of the others."""

import pytest
from compare import rows

from patternldp.queries import flagship, methods, relational, streams, workloads  # noqa: F401
from patternldp.sqlapi import parse_call

CHOSEN = [f"wk_dp_opt{k}_copurchase" for k in (2, 4)] + ["wk_dp_rounds3_trade", "edge_count_dp_trade", "pt_dp3_trade", "tree_dp_d22_copurchase", "tree_dp_fork_alt_copurchase", "star_dp4_trade", "star_dp_debiased3_copurchase", "marks_4_copurchase", "rr_enum_pt2_nation_region", "rr_enum_wk2_distinct_nation_region", "rr_star_3_nation_region", "clip_wk3_trade", "cap_star3_trade", "comm_fork_trade", "ops_pt4_trade", "bounds_3_trade", "theory_trade", "privacy_loss_fork_trade", "protocol_pt2_trade", "decompose_pt2_trade", "nrep_pt2_trade", "exact_tree_d22_trade_sparse", "closed_fork_copurchase", "graph_stats_near_vectors", "build_arcs_page_links", "exact_pt4_turns", "build_arcs_turns", "build_arcs_handoff", "protocol_pt5_trade_sparse", "protocol_d212_trade_sparse", "rootings_fork_trade_sparse", "improve_wk3_trade", "improve_star3_trade", "wk_dp_opt6_handoff", "clip_wk5_handoff", "rr_walk_5_handoff", "pt_marked3_trade", "tree_marked_d22_copurchase", "tree_dp_labelled_fork_trade", "decompose_fork_copurchase", "nrep10_fork_trade_sparse", "comm_methods_trade", "ops_wk4_trade", "tail_bounds", "central_laplace_star3_trade", "privacy_loss_central_star3_trade", "rr_tree_marked_fork_handoff"]


def check(module, name, spark, sf, duck):
    got = module.QUERIES[name](spark, sf).toPandas()
    want = duck.sql(module.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", CHOSEN)
def test_methods(name, spark, sf, duck):
    check(methods, name, spark, sf, duck)


def test_flagship(spark, sf, duck):
    check(flagship, "flagship_fork_copurchase", spark, sf, duck)


@pytest.mark.parametrize("name", sorted(relational.ORACLES))
def test_relational(name, spark, sf, duck):
    check(relational, name, spark, sf, duck)


@pytest.mark.parametrize("name", ["stream_degree", "stream_edges_dedup", "stream_late_drop", "udf_grouped_exact_paths", "udtf_free_trees", "udtf_comm_model", "sql_dp_tree_call", "stream_star_weeks_batch", "stream_star_window", "stream_foreach_walk"])
def test_streams_and_functions(name, spark, sf, duck):
    check(streams, name, spark, sf, duck)


@pytest.mark.parametrize("name", ["stream_tumbling_pairs", "stream_sliding_users", "stream_session_users"])
def test_streams_return_every_window(name, spark, sf, duck):
    """Against SQL over all events, the last days included."""
    check(streams, name, spark, sf, duck)


def test_weeks_of_many_files_stay_whole_batches(spark, sf):
    got = streams.streams.drained(streams.streams.tumbling_counts(streams.streams.event_stream(spark, sf, file_rows=10, closing=True)), "many")
    one = streams.streams.drained(streams.streams.tumbling_counts(streams.streams.event_stream(spark, sf, closing=True)), "one")
    assert rows(got.toPandas()) == rows(one.toPandas()) and got.agg({"n": "sum"}).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()


def test_sql_calls():
    assert parse_call("walk", "'trade', 3, 1.0") == ("walk", "trade", 3, 1.0, 42)
    with pytest.raises(ValueError):
        parse_call("tree", "'trade', 3, 1.0")


def test_every_core_query_has_its_sql():
    known = methods.QUERIES | relational.QUERIES | streams.QUERIES | flagship.QUERIES
    sqls = methods.ORACLES | relational.ORACLES | streams.ORACLES | flagship.ORACLES
    print(sorted(set(known) - set(sqls)))
    assert not {q for q in set(known) - set(sqls) if q.startswith(("rr_", "improve_", "stream_", "protocol_", "nrep", "decompose_", "central_"))}
