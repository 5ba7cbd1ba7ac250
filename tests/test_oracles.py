"""A cross-section of the registered queries against their SQL; the driver runs all of them."""

import pytest
from oracle import check

from semtrie import catalog

KEYS = """first_access_commerce split_assignment split_by_time corpus_users passage_targets user_profiles_interest hash_ngram_checksum max_cooccurrence_commerce
exact_neighbors_vectors two_means_root trie_placements trie_placements_outer_loop trie_clone_on_split trie_metric_unit clone_stats_by_delta join_new_users insert_into_live_trie stream_into_live_trie stream_trie_join drift_reroute udtf_trie_paths contacts_bfs expand_round3
expand_single_reply query_noise forest_by_language merge_sparse recall_random_lists pa_edges ring_successor chain_hop_trace chain_hop_distributed chain_hop_revisit random_query_expected diffuse_alpha_05 min_hops_trie custodians departures_reelect
join_asof_purchase join_interval_access agg_rollup_lang_source win_range_7_days vec_functions path_functions string_functions join_cross_landmarks agg_kll_quantiles stream_tumbling stream_profiles""".split()


@pytest.mark.parametrize("name", KEYS)
def test_query_equals_sql(spark, sf01, name):
    check(catalog.queries()[name], catalog.oracle_sql()[name], spark, sf01)


def test_every_oracle_has_a_query():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())
    assert len(catalog.oracle_sql()) > 100


def test_queries_load_before_any_session():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    code = "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)
