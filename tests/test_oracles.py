"""A sample of the registered queries against DuckDB on the smallest tables; the whole registry runs in the driver's check."""

import pytest

from graphwave import catalog
from tests.oracle import connect, differences

SAMPLE = [
    "tree_order_part", "tree_star", "tree_wah_sieved_order_part", "tree_auto_order_part", "paths_order_part", "needs_order_part", "receivers_bound_star", "sieve_ratio_kron",
    "ledger_wah_sieved_order_part", "payload_ledger_wah_allgather_order_part", "wah_words_16_order_part", "codec_plwah", "codec_rle", "codec_varint", "codec_compare", "w4_compare", "factor_compare",
    "ledger_pull_order_part", "ledger_grid_order_part", "encoding_choice", "amortisation", "w2_published_counts", "w9_toy_spmv", "w10_toy_sieve", "w11_toy_pull", "w12_wah_example",
    "w13_kron_edges", "w15_spmv_many", "w16_betweenness_toy8", "w16_components_links", "lemma_input_mask", "op_join_as_of", "op_join_interval", "op_join_nearest", "st_chain_stream", "st_directory_stream",
]


@pytest.fixture(scope="module")
def con(tiny):
    return connect(tiny)


@pytest.mark.parametrize("name", SAMPLE)
def test_query(spark, tiny, con, name):
    assert differences(catalog.queries()[name](spark, tiny), con, catalog.oracle_sql()[name]) == ""


def test_registry_is_consistent():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())
    assert len(catalog.queries()) > 250
