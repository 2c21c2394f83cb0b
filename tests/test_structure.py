"""What the shape of a query says, without Spark."""

import random

import pytest

from optjoin import algebra as al
from optjoin import workloads
from optjoin.functions import bits
from optjoin.plans import structure as st


def test_block_graph_of_six_blocks():
    names, one, two = st.block_graph(workloads.QUERIES["nested6"].body)
    assert names == ["a", "b", "c", "d", "e", "f"]
    assert set(one) == {("a", "b"), ("c", "d"), ("e", "f"), ("a", "e")}
    assert two == [("a", "c")]


def test_peers_are_coalesced():
    nodes = st.block_tree(workloads.QUERIES["nested6"].body)
    assert nodes[0].name == "a+c"
    assert sorted(x.name for x in nodes[1:]) == ["b", "d", "e", "f"]


def _composite():
    return [p for p in workloads.QUERIES["composite_acyclic"].body.patterns]


def test_composite_labels_are_acyclic_though_the_variable_graph_is_not():
    nodes = [st.Node("", _composite())]
    names = [p.name for p in _composite()]
    assert st.acyclic(names, st.links(nodes))
    assert not st.variable_graph_acyclic(_composite())


def test_leaves_attach_to_the_covering_neighbour():
    nodes = [st.Node("", _composite())]
    order = st.removal_order([p.name for p in _composite()], st.links(nodes), {"P1": 1, "P2": 2, "P3": 3, "P4": 99})
    assert all(to == "P4" for x, to in order[:3])


@pytest.mark.parametrize("name,repair", [("q1", False), ("nested6", False), ("two_class", True), ("cyclic_core", False), ("cyclic_child", True), ("parent_linked", True)])
def test_decisions(name, repair):
    assert st.repair_required(st.block_tree(workloads.QUERIES[name].body)).repair is repair


def test_the_printed_decision_misses_parent_linked_children():
    assert not st.repair_required_literal(st.block_tree(workloads.QUERIES["parent_linked"].body)).repair


def test_ill_formed_queries_are_refused():
    a, b, c = (al.block(al.pattern(n, "t", **v)) for n, v in (("A", {"x": "?x"}), ("B", {"x": "?x", "y": "?y"}), ("C", {"y": "?y", "z": "?z"})))
    with pytest.raises(al.NotWellDesigned):
        al.check_optional(al.Join(al.LeftJoin(a, b), c))
    with pytest.raises(al.NotWellDesigned):
        al.check_filters(al.Filter(a, "q > 1", frozenset({"q"})))


def test_row_codes():
    assert bits.run_lengths("1110011110") == [1, 3, 2, 4, 1]
    assert bits.run_lengths("0010010000") == [0, 2, 1, 2, 1, 4]
    assert bits.hybrid("0010010000") == ("positions", [3, 6])
    assert bits.hybrid("1110011110")[0] == "runs"
    draw = random.Random(3)
    for _ in range(200):
        row = "".join(draw.choice("01") for _ in range(draw.randrange(1, 40)))
        kind, data = bits.hybrid(row)
        assert bits.decode(kind, data, len(row)) == row


def test_normal_form_counts_arms():
    assert len(al.normal_form(workloads.QUERIES["q2_union"].body)) == 2
    assert len(al.normal_form(workloads.QUERIES["union_flags"].body)) == 2
