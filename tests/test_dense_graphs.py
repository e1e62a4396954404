"""The co-order and supplier graphs hold the links of all orders."""

import pytest

from wavefront.plans.graph_queries import QUERIES
from wavefront.sources.tables import table

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name,key", [("coorder", "l_partkey"), ("supplier", "l_suppkey")])
def test_every_order_has_its_links(spark, name, key):
    have = {(r.fid, r.tid) for r in QUERIES[f"g_{name}_dense_edges"](spark, SF).collect()}
    lines = table(spark, SF, "lineitem").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice").collect()
    for a, b in zip(lines, lines[1:], strict=False):
        if a.l_orderkey == b.l_orderkey and a[key] != b[key]:
            assert (a[key], b[key]) in have
