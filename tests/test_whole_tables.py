"""Relational queries read all orders."""

import pytest

from wavefront.plans.relational_queries import QUERIES
from wavefront.sources.tables import table

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["rel_explode_paths", "rel_fn_array", "rel_path_edges", "rel_udtf_path_edges", "rel_window_rank", "rel_window_row_number", "rel_window_dense_rank", "rel_fn_math"])
def test_all_orders_are_read(spark, name):
    line = table(spark, SF, "lineitem")
    rows, orders = line.count(), line.select("l_orderkey").distinct().count()
    want = orders if name == "rel_fn_array" else rows - orders if name.endswith("path_edges") else rows
    assert QUERIES[name](spark, SF).count() == want
