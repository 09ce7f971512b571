"""Plans: what is scanned, and what must not be in them."""

from __future__ import annotations

import re

import pytest

from gradsift.catalog import QUERIES

SF = "/root/testdata/sf0.001"


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark):
    p = plan(QUERIES["scan_parquet_pruned"](spark, SF))
    assert "PushedFilters: [IsNotNull(source), EqualTo(source,src1)]" in p
    assert re.search(r"ReadSchema: struct<lang:string,source:string,n_chars:bigint>", p)


def test_rating_is_one_scan_in_generated_code(spark):
    p = plan(QUERIES["rate_linear"](spark, SF))
    assert "Exchange" not in p and "Python" not in p and "ReadSchema: struct<doc_id:bigint,text:string>" in p


@pytest.mark.parametrize("name", ["global_rank", "prune_shifted_gaussian", "prune_random", "bench_lineitem_select", "selection_overlap", "join_sortmerge", "interval_join_events"])
def test_no_single_partition_and_no_cartesian(spark, name):
    p = plan(QUERIES[name](spark, SF))
    assert "CartesianProduct" not in p
    if name not in ("selection_overlap",):  # ends in one row
        assert "SinglePartition" not in p


def test_parameters_are_broadcast(spark):
    assert "BroadcastHashJoin" in plan(QUERIES["join_broadcast_params"](spark, SF))
    assert "BroadcastNestedLoopJoin" in plan(QUERIES["cross_grid"](spark, SF))
