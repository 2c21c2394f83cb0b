"""Operators whose plans depend on sizes, and those moved onto given tables."""

import pytest

from conftest import SMALL, same
from optjoin import metrics, registry

MOVED = ["null_compat_join", "null_empty_mapping", "null_minimum_union", "op_o06_values"]


@pytest.mark.parametrize(("limit", "join"), [("10485760", "BroadcastHashJoin"), ("1000", "SortMergeJoin")])
def test_a_side_is_sent_only_if_it_fits(spark, duck, limit, join):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    try:
        df = registry.QUERIES["op_o29_broadcast"](spark, SMALL)
        plan = df._jdf.queryExecution().sparkPlan().toString()
        assert [x for x in ("BroadcastHashJoin", "SortMergeJoin") if x in plan] == [join]
        same(df, duck, registry.ORACLES["op_o29_broadcast"])
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


@pytest.mark.parametrize("name", MOVED)
def test_given_tables_are_read(spark, duck, name):
    df = registry.QUERIES[name](spark, SMALL)
    assert metrics.scan_count(df) > 0 and df.count() > 100
    same(df, duck, registry.ORACLES[name])
