"""Operators over whole tables: nothing is left out by id, and rows equal the oracle's where ids go far."""

import pytest

from graphwave import catalog
from graphwave.plans.registry import graph
from tests.oracle import connect, differences

SMALL = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def con():
    return connect(SMALL)


WINDOWS = ["op_window_rank", "op_window_dense_rank", "op_window_percent_rank", "op_window_cume_dist", "op_window_ntile", "op_window_lag_lead", "op_agg_collect"]
OTHERS = ["op_join_full", "w16_hops", "op_filter_subgraph", "op_join_hash", "op_join_merge", "op_join_broadcast", "op_agg_approx", "codec_bbc", "payload_pull_order_part", "needs_delta_events", "st_search_after_batch", "st_distinct_edges_stream", "tree_wah_pull_order_part", "tree_grid_3x2_order_part", "tree_auto_kron", "reach_hierarchy", "w3_ladder_wah_sieved", "w5_sweep_wah_allgather"]


@pytest.mark.parametrize("name", [*WINDOWS, *OTHERS])
def test_oracle(spark, con, name):
    assert differences(catalog.queries()[name](spark, SMALL), con, catalog.oracle_sql()[name]) == ""


def test_no_vertex_is_left_out(spark):
    n = graph(spark, SMALL, "order_part").edges.select("src").distinct().count()
    assert n > 2_000
    for name in WINDOWS:
        assert catalog.queries()[name](spark, SMALL).count() == n
    assert catalog.queries()["w16_hops"](spark, SMALL).count() == graph(spark, SMALL, "star").n
    assert catalog.queries()["op_filter_subgraph"](spark, SMALL).count() > 0


def test_full_join_has_unmatched_keys_on_both_sides(spark):
    rows = catalog.queries()["op_join_full"](spark, SMALL).collect()
    assert any(r["a"] is None for r in rows) and any(r["b"] is None for r in rows) and any(r["a"] and r["b"] for r in rows)
    edges = graph(spark, SMALL, "order_part").edges
    assert sum((r["a"] or 0) * r["k"] for r in rows) == edges.count()
    assert sum(r["b"] or 0 for r in rows) == catalog.queries()["tree_order_part"](spark, SMALL).count()


@pytest.mark.parametrize("op", ["and", "or", "not", "count", "andnot"])
def test_word_operations_on_sets_that_overlap(spark, con, op):
    assert differences(catalog.queries()[f"wah_{op}"](spark, SMALL), con, catalog.oracle_sql()[f"wah_{op}"]) == ""
    found = catalog.queries()[f"wah_{op}"](spark, SMALL).collect()
    assert max(r["owner_block"] for r in found) == graph(spark, SMALL, "order_part").blocks - 1
    if op == "and":
        assert any(r["word_hex"] < "80000000" and r["word_hex"] != "00000000" for r in found)


def test_range_join_reaches_every_id(spark, con):
    assert differences(catalog.queries()["op_join_range"](spark, SMALL), con, catalog.oracle_sql()["op_join_range"]) == ""
    large = "/root/testdata/sf0.1"
    rows = catalog.queries()["op_join_range"](spark, large)
    assert rows.count() == catalog.queries()["tree_order_part"](spark, large).count() > 40_000
    assert rows.where("block * block > vid or (block + 1) * (block + 1) <= vid").count() == 0


def test_break_even_of_the_smallest_graph_follows_its_table(spark, con, tmp_path):
    assert differences(catalog.queries()["breakeven_toy8"](spark, SMALL), con, catalog.oracle_sql()["breakeven_toy8"]) == ""
    assert catalog.queries()["breakeven_toy8"](spark, SMALL).first()["bitmap_bits"] == 3 * 8
    spark.read.parquet(f"{SMALL}/orders.parquet").where("o_orderstatus <> 'P'").write.parquet(f"{tmp_path}/orders.parquet")
    assert catalog.queries()["breakeven_toy8"](spark, str(tmp_path)).first()["bitmap_bits"] == 3 * 7
    assert differences(catalog.queries()["breakeven_toy8"](spark, str(tmp_path)), connect(str(tmp_path)), catalog.oracle_sql()["breakeven_toy8"]) == ""
