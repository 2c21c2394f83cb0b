"""Query texts, files, functions in Python form, and every other registered operator, against SQL or brute force."""

import pytest

from conftest import SMALL, same
from optjoin import algebra as al
from optjoin import registry
from optjoin.functions.bits import hybrid
from optjoin.operators.surface import OPERATORS
from optjoin.parser import evaluate, parse, parse_query
from optjoin.sources.files import read_nt, write_nt
from optjoin.sources.tables import Catalog

NAMES = sorted(n for n, (_, sql) in OPERATORS.items() if sql) + ["stream_o78_optional"]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    same(registry.QUERIES[name](spark, SMALL), duck, registry.ORACLES[name])


def test_row_codes(spark):
    bits = {}
    for r in spark.read.parquet(f"{SMALL}/orders.parquet").orderBy("o_orderkey").collect():
        bits[r.o_custkey] = bits.get(r.o_custkey, "") + str(int(r.o_orderpriority == "1-URGENT"))
    want = {k: " ".join([hybrid(b)[0], *map(str, hybrid(b)[1])]) for k, b in bits.items()}
    assert {r.o_custkey: r.code for r in registry.QUERIES["op_o81_row_code"](spark, SMALL).collect()} == want


def test_shape_of_a_text():
    q = parse_query('SELECT ?a { { t(x: ?a) } UNION { u(x: ?a) } . v(x: ?a, "y + 1": 3) OPTIONAL { w(x: ?a, z: ?b) FILTER(?b > 1 || BOUND(?a)) } }')
    assert al.serialize(q) == "a <- ((([p1] union [p2]) join [p3]) opt filter([p4], `b` > 1 OR (`a` IS NOT NULL)))"
    assert parse("SELECT * { ?s <p> ?o } ORDER BY ?s DESC(?o) OFFSET 2 LIMIT 3").order == (("s", False), ("o", True))


@pytest.mark.parametrize("text", ["", "SELECT ?a {}", "SELECT ?b { t(x: ?a) }", "SELECT ?a { OPTIONAL { t(x: ?a) } }", "SELECT ?a { t(x: ?a) ", "SELECT ?a { t(x: ?a) } extra", "SELECT ?a { t(x ?a) }", "SELECT ?a { t(x: ?a) FILTER(?a > 1 }", "SELECT ?a { ~ }", "SELECT ?a { BIND(1 AS ?a) }", "SELECT ?a { t(x: ?a) BIND(1 AS ?a) }", "SELECT ?b { t(x: ?a) BIND(?q + 1 AS ?b) }", "SELECT ?b { t(x: ?a) BIND(?a + 1 AS ?b) u(x: ?a) }", "SELECT ?b { t(x: ?a) OPTIONAL { u(x: ?a) BIND(?a + 1 AS ?b) } }"])
def test_unreadable_texts(text):
    with pytest.raises(al.QueryError):
        parse(text)


def test_computed_constants(spark):
    rows = evaluate(Catalog(spark, SMALL), 'SELECT ?k { region(r_regionkey: ?r) BIND("a\\nb" AS ?k) }').collect()
    assert [r.k for r in rows] == ["a\nb"] * 5


def test_lines_round_trip(spark, tmp_path):
    rows = [("a", "p", 'x "y" \\n \\ z'), ("b", "p", ""), ("c", "p", "two\nlines\tand\rmore \\"), ("d", "q", "node")]
    df = spark.createDataFrame(rows, "s string, p string, o string")
    write_nt(df, str(tmp_path / "nt"), df["p"] == "q")
    assert sorted(map(tuple, read_nt(spark, str(tmp_path / "nt")).collect())) == sorted(rows)


def test_a_broken_line_fails(spark, tmp_path):
    (tmp_path / "x.nt").write_text("# a comment\n\n<a> <b> <c> .\nnonsense\n")
    with pytest.raises(Exception, match="not a triple"):
        read_nt(spark, str(tmp_path)).collect()
