"""Queries of the cost model read the given tables: their rows follow them, and without them there are none."""

from __future__ import annotations

import pytest
from pyspark.errors import AnalysisException

from evenlane.queries import ORACLE_SQL, QUERIES
from tests.compare import assert_same, tables

TABLES = (
    "advisor_table",
    "bitonic_schedule_table",
    "broadcast_schedule_table",
    "calibrate",
    "claim_sample_size",
    "cost_broadcast_table",
    "cost_prefix_table",
    "earlier_results",
    "odd_even_schedule_table",
    "optimality_table",
    "prefix_schedule_table",
    "published_phase_shares",
)


@pytest.mark.parametrize("name", TABLES)
def test_rows_follow_the_table(spark, data, tmp_path, name):
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path)).collect()
    small, more = QUERIES[name](spark, "/root/testdata/sf0.001"), QUERIES[name](spark, data)
    assert small.collect() != more.collect()
    if name in ORACLE_SQL:
        assert_same(small, tables("/root/testdata/sf0.001"), ORACLE_SQL[name])
        assert_same(more, tables(data), ORACLE_SQL[name])
