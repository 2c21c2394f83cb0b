"""The engine against plain SQL and against brute force on small random queries."""

import itertools
import random

import pytest

from conftest import SMALL, same
from optjoin import algebra as al
from optjoin import registry
from optjoin.engine import Catalog, run

NAMES = sorted(n for n in registry.ORACLES if n.startswith(("core_", "union_", "filter_", "distinct_", "toy_", "null_", "graph_")))


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    same(registry.QUERIES[name](spark, SMALL), duck, registry.ORACLES[name])


def _brute(tree, tables):
    if isinstance(tree, al.Block):
        rows = [{}]
        for p in tree.patterns:
            made = [dict(zip((t[1:] for _, t in p.cols), r, strict=True)) for r in tables[p.table]]
            rows = [{**a, **b} for a, b in itertools.product(rows, made) if all(a[k] == b[k] for k in a.keys() & b.keys())]
        return rows
    left, right = _brute(tree.left, tables), _brute(tree.right, tables)
    out = []
    for a in left:
        near = [{**a, **b} for b in right if all(a[k] == b[k] for k in a.keys() & b.keys() if a[k] is not None and b[k] is not None)]
        out += near or ([a] if isinstance(tree, al.LeftJoin) else [])
    return out


def test_random_optional_queries(spark):
    draw = random.Random(5)
    shapes = [
        (("M", "ab"), [("S1", "abc"), ("S2", "ad")]),
        (("M", "ab"), [("S1", "ac"), ("S2", "bd")]),
        (("M", "ab"), [("S1", "bc"), ("S2", "cd")]),
        (("M", "ab"), [("S1", "ac"), ("S2", "cb")]),
    ]
    for core, child in shapes:
        tables, patterns = {}, {}
        for name, v in [core, *child]:
            tables[name] = sorted({tuple(draw.randrange(3) for _ in v) for _ in range(5)})
            patterns[name] = al.Pattern(name, name, tuple((f"c{i}", f"?{x}") for i, x in enumerate(v)))
        tree = al.LeftJoin(al.block(patterns["M"]), al.block(*(patterns[n] for n, _ in child)))
        every = sorted(al.variables(tree))
        catalog = Catalog(spark, None, {n: spark.createDataFrame(rows, ", ".join(f"c{i} int" for i in range(len(rows[0])))) for n, rows in tables.items()})
        want = sorted((tuple(r.get(v) for v in every) for r in _brute(tree, tables)), key=repr)
        for options in ({}, {"best_match": "mask"}, {"reduce": "off", "force_repair": True}):
            got = sorted((tuple(r) for r in run(catalog, al.Query(tree, tuple(every)), **options).collect()), key=repr)
            assert got == want, (core, child, options)


def test_products_at_a_hub_lose_correlation(spark):
    frames = {"X": [("s1", "x1"), ("s2", "x1")], "Y": [("s1", "y1"), ("s2", "y2")], "Z": [("s1", "z1"), ("s2", "z2")]}
    catalog = Catalog(spark, None, {n: spark.createDataFrame(r, f"s string, {n.lower()} string") for n, r in frames.items()})
    body = al.block(*(al.Pattern(n, n, (("s", "?s"), (n.lower(), "?" + n.lower()))) for n in frames))
    query = al.Query(body, ("x", "y", "z"), True)
    assert run(catalog, query).count() == 2
    assert run(catalog, query, mode="literal").count() == 4


def test_disconnected_queries_are_refused(spark):
    catalog = Catalog(spark, SMALL)
    body = al.LeftJoin(al.block(al.pattern("R", "region", r_regionkey="?r")), al.block(al.pattern("P", "part", p_partkey="?p")))
    with pytest.raises(al.Disconnected):
        run(catalog, al.Query(body, ("r", "p")))


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
