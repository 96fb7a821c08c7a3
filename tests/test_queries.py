"""Queries against their SQL: a selection by default, all of them with EVENLANE_ALL=1."""

from __future__ import annotations

import os

import pytest

from evenlane.queries import ORACLE_SQL, QUERIES
from tests.compare import assert_same, tables

SOME = (
    "regular_sort_partkey regular_sort_returnflag regular_sort_multikey regular_sort_nulls regular_sort_padded regular_sort_tagless random_sort_price classic_sort_integer random_sort_two_step "
    "inplace_regular_sort inplace_random_sort inplace_iterated_sort advised_sort iterated_sort_m2 kway_rounds_sort two_round_sort tag_all_sort bitonic_sort_orders column_sort_events comparator_sort "
    "regular_sample_padded random_sample_exact sample_sorted_bitonic sample_sorted_recursive fences_regular_returnflag split_tree split_cuts split_merge split_search count_matrix prefix_tree prefix_doubling "
    "routed_blocks bucket_sizes_tag_all h_relation rounds_by_method tag_overhead imbalance_by_samples claim_rate input_worst sizes_input_dupes theory_regular cost_broadcast_table cost_prefix_table "
    "odd_even_schedule_table broadcast_schedule_table prefix_schedule_table claim_sample_size ledger_regular ledger_presorted_random ledger_classic_random earlier_results advisor_table optimality_table "
    "topk_price quartiles global_rank_hot_keys global_dense_rank global_running_quantity dedup_first_by_key dedup_sorted_neighbours fenced_merge_join fenced_anti_join fenced_range_join asof_events merge_two_sorted "
    "sorted_aggregate sorted_except approx_measures sample_rates reservoir_sample udf_search heap_merge fold_merge udtf_schedule fenced_range_read sorted_sink bucketed_join source_text "
    "stream_sorted_batches stream_tumbling stream_sliding stream_sessions stream_fence_drift stream_steady_fences stream_late_rows phase_profile_rival"
).split()
NAMES = sorted(QUERIES) if os.environ.get("EVENLANE_ALL") else SOME


@pytest.fixture(scope="module")
def con(data):
    return tables(data)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, data, con, name):
    df = QUERIES[name](spark, data)
    if name in ORACLE_SQL:
        assert_same(df, con, ORACLE_SQL[name])
    else:
        assert df.count() > 0


def test_every_query_has_sql_or_is_timed():
    timed = ("bench_", "phase_", "observed_g", "calibrate", "predicted_")
    assert [n for n in QUERIES if n not in ORACLE_SQL and not n.startswith(timed)] == []
