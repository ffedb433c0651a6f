"""A part of the registered queries against DuckDB on the smallest tables; tests/oracle.py runs all of them."""

import pytest
from oracle import compare, connect

import __spark_entry__ as entry

NAMES = ["range_2d_10", "range_3d_50", "smooth_range_100", "dense_embeddings_range", "constant_array_range", "member_dim", "multi_attr", "batch_queries", "progressive_levels", "estimate_bounds", "baseline_rect_clip", "baseline_dim_columns", "rect_clip_rectangles", "z_codes", "leaf_bins_equi_depth", "double_range_started", "double_range_ended", "dim_masks", "bin_signs", "reduced_nodes_equi_depth", "trace_levels", "blocks_read", "estimate_error", "estimate_members", "modify_cells", "sum_gauss_grid", "gauss_sparse_3d", "stream_bounds", "session_cells", "set_ops", "overlap_boxes", "value_runs", "chunk_quantiles", "payload_positions", "stream_dedup"]


@pytest.fixture(scope="module")
def duck(sf_dir):
    return connect(sf_dir)


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, sf_dir, duck, name):
    assert compare(entry.queries()[name](spark, sf_dir), duck, entry.oracle_sql()[name]) is None


def test_entry(spark):
    assert entry.entry(spark).columns == ["partkey", "suppkey", "value"]
    assert set(entry.oracle_sql()) <= set(entry.queries())
