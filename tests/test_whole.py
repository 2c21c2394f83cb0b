"""Queries whose answers grow fastest, over whole tables."""

import pytest

from conftest import SMALL, same
from optjoin import registry

NAMES = sorted(n for n in registry.ORACLES if n.endswith(("nested6", "parent_linked", "union_subsumed_kept")))


@pytest.mark.parametrize("name", NAMES)
def test_whole_query_equals_sql(spark, duck, name):
    assert "< 300" not in registry.ORACLES[name] and "< 20" not in registry.ORACLES[name] and "< 5" not in registry.ORACLES[name]
    same(registry.QUERIES[name](spark, SMALL), duck, registry.ORACLES[name])
