"""Queries of every part of the catalogue against DuckDB; the driver compares all of them."""

import pytest

KEYS = [
    "portable_hash", "gen_uni_a", "gen_tree_a", "gen_tier_b", "natural_n3", "policy_profile_n1", "policy_profile_h1", "access_classes", "sharing_degree_uni", "role_closure", "rls_scan_sql", "gen_queries",
    "part_user_sizes", "storage_delta", "candidate_moves_h1", "plan_n1", "plan_exact_gap", "route_first_pick", "route_cover", "cost_user_mod4", "selectivity_avg_of_ratios_mod4", "recall_model_grid", "ef_for_target", "mem_saving",
    "ground_truth_topk", "secure_topk_single", "secure_topk_split", "secure_topk_splitree", "recall_at_k_post_rls_50", "ivf_label_probe", "topk_underfull", "upd_revoke_docs", "upd_state_violations", "upd_dirty_partitions", "upd_refresh_route", "upd_repartition_advice",
    "join_asof_policy", "agg_cube", "win_range_frame", "bitmap_auth_size", "stream_state_vs_batch", "stream_session", "stream_interval_join", "stream_member_states", "stream_secure_search",
    "join_bucketed", "index_reload", "stream_late_repair",
]


@pytest.mark.parametrize("key", KEYS)
def test_equals_sql(same, key):
    same(key)


def test_entry_and_catalogue(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).columns == ["query_id", "rank", "doc_id", "dist"]
