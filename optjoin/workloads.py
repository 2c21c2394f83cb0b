"""The worked queries re-expressed on the given tables, each with the plain SQL it is held against."""

from __future__ import annotations

from .algebra import Filter, Join, LeftJoin, Query, Union, block, pattern

LID = {"concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity)": "?l"}
_LSQL = "concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity)"


def line(name: str, where: str | None = None, identity: bool = True, **cols: object):
    p = pattern(name, "lineitem", where, **cols)
    return type(p)(name, "lineitem", p.cols + (tuple(LID.items()) if identity else ()), where, "bag" if identity else "set")


def distinct_pattern(name: str, table: str, where: str | None = None, **cols: object):
    return pattern(name, table, where, "set", **cols)


def _opt(core, child):
    return LeftJoin(core, child)


C = pattern("C", "customer", c_custkey="?c")
CN = pattern("C", "customer", c_custkey="?c", c_nationkey="?n")
O = pattern("O", "orders", o_orderkey="?o", o_custkey="?c")  # noqa: E741
PURCHASES = pattern("E", "events", event_id="?e", user_id="?c", event_type="purchase")
SUPPLIER_N = pattern("S", "supplier", s_suppkey="?s", s_nationkey="?n")

QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def _add(name: str, body, select: str, sql: str, distinct: bool = False, **options: object) -> None:
    QUERIES[name] = Query(body, tuple(select.split()), distinct, options)
    SQL[name] = sql


_add(
    "q1",
    _opt(block(pattern("T1", "customer", c_custkey="?c", c_nationkey=7)), block(O, pattern("F", "orders", o_orderkey="?o", o_orderstatus="F"))),
    "c o",
    "SELECT c_custkey AS c, o_orderkey AS o FROM customer LEFT JOIN (SELECT a.* FROM orders a JOIN orders b ON a.o_orderkey = b.o_orderkey AND b.o_orderstatus = 'F') x ON o_custkey = c_custkey WHERE c_nationkey = 7",
)
_add(
    "q1_low",
    _opt(block(C), block(pattern("O", "orders", o_orderkey="?o", o_custkey="?c", o_orderpriority="1-URGENT"), line("L", l_orderkey="?o", l_returnflag="R"))),
    "c o",
    "SELECT c_custkey AS c, o_orderkey AS o FROM customer LEFT JOIN (SELECT * FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderpriority = '1-URGENT' AND l_returnflag = 'R') x ON o_custkey = c_custkey",
)
_add(
    "q1_tail",
    _opt(block(pattern("O", "orders", o_orderkey="?o")), block(line("L", l_orderkey="?o", l_suppkey="?s"), pattern("S", "supplier", s_suppkey="?s", s_nationkey=7))),
    "o s",
    "SELECT o_orderkey AS o, l_suppkey AS s FROM orders LEFT JOIN (SELECT * FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey = 7) x ON l_orderkey = o_orderkey",
)
_add(
    "q2_union",
    _opt(
        Join(
            block(distinct_pattern("T1", "orders", o_orderkey="?o", o_custkey=42)),
            Union(block(line("A", None, False, l_orderkey="?o", l_suppkey="?s")), block(line("B1", None, False, l_orderkey="?o", l_partkey="?p"), line("B2", None, False, l_partkey="?p", l_suppkey="?s"))),
        ),
        block(distinct_pattern("S", "supplier", s_suppkey="?s", s_nationkey="?n"), distinct_pattern("N", "nation", n_nationkey="?n", n_regionkey=3)),
    ),
    "o s p n",
    """WITH u AS (SELECT DISTINCT l_orderkey o, l_suppkey s, NULL::BIGINT p FROM lineitem UNION ALL
      SELECT a.o, b.s, a.p FROM (SELECT DISTINCT l_orderkey o, l_partkey p FROM lineitem) a JOIN (SELECT DISTINCT l_partkey p, l_suppkey s FROM lineitem) b ON a.p = b.p)
    SELECT u.o, u.s, u.p, x.n FROM (SELECT o_orderkey FROM orders WHERE o_custkey = 42) t JOIN u ON u.o = t.o_orderkey
    LEFT JOIN (SELECT s_suppkey, s_nationkey AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey WHERE n_regionkey = 3) x ON x.s_suppkey = u.s""",
)
_add(
    "nested6",
    LeftJoin(
        Join(
            LeftJoin(block(pattern("a", "customer", c_custkey="?c", c_nationkey="?n", c_mktsegment="BUILDING")), block(pattern("b", "events", event_id="?e", user_id="?c", event_type="purchase"))),
            LeftJoin(block(pattern("c", "orders", o_orderkey="?o", o_custkey="?c", o_orderpriority="1-URGENT")), block(line("d", l_orderkey="?o", l_partkey="?k", l_returnflag="R"))),
        ),
        LeftJoin(block(pattern("e", "supplier", "s_acctbal > 5000", s_suppkey="?s", s_nationkey="?n")), block(type(C)("f", "nation", (("n_nationkey", "?n"), ("n_regionkey", 2), ("n_name", "?nf"))))),
    ),
    "c n e o k s nf",
    """SELECT c_custkey c, c_nationkey n, event_id e, o_orderkey o, l_partkey k, s_suppkey s, n_name nf FROM customer
    LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') ON user_id = c_custkey
    JOIN (SELECT * FROM orders WHERE o_orderpriority = '1-URGENT') ON o_custkey = c_custkey
    LEFT JOIN (SELECT * FROM lineitem WHERE l_returnflag = 'R') ON l_orderkey = o_orderkey
    LEFT JOIN (SELECT s_suppkey, s_nationkey, n_name FROM supplier LEFT JOIN nation ON n_nationkey = s_nationkey AND n_regionkey = 2 WHERE s_acctbal > 5000) ON s_nationkey = c_nationkey
    WHERE c_mktsegment = 'BUILDING'""",
)
_add(
    "composite_acyclic",
    block(
        line("P1", "l_quantity < 25", False, l_orderkey="?o", l_partkey="?p"),
        line("P2", "l_discount > 0.02", False, l_partkey="?p", l_suppkey="?s"),
        line("P3", "l_returnflag = 'R'", False, l_suppkey="?s", l_orderkey="?o"),
        line("P4", None, False, l_orderkey="?o", l_partkey="?p", l_suppkey="?s"),
    ),
    "o p s",
    """SELECT DISTINCT d.l_orderkey o, d.l_partkey p, d.l_suppkey s FROM lineitem d
    WHERE EXISTS (SELECT 1 FROM lineitem x WHERE x.l_quantity < 25 AND x.l_orderkey = d.l_orderkey AND x.l_partkey = d.l_partkey)
    AND EXISTS (SELECT 1 FROM lineitem x WHERE x.l_discount > 0.02 AND x.l_partkey = d.l_partkey AND x.l_suppkey = d.l_suppkey)
    AND EXISTS (SELECT 1 FROM lineitem x WHERE x.l_returnflag = 'R' AND x.l_suppkey = d.l_suppkey AND x.l_orderkey = d.l_orderkey)""",
)

_W6 = _opt(
    block(pattern("C", "customer", c_custkey="?c", c_acctbal="?b", c_mktsegment="BUILDING"), O),
    block(line("L", l_orderkey="?o", l_suppkey="?s"), pattern("S", "supplier", s_suppkey="?s", s_nationkey=7)),
)
_W6SQL = "SELECT c_custkey c, o_orderkey o, c_acctbal b, l_suppkey s FROM customer JOIN orders ON o_custkey = c_custkey LEFT JOIN (SELECT * FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey = 7{on}) x ON l_orderkey = o_orderkey WHERE c_mktsegment = 'BUILDING'{where}"
_two = Filter(Filter(_W6, "s <> 22", frozenset({"s"})), "b < 2000", frozenset({"b"}))
_add("filter_sparql", _two, "c o b s", _W6SQL.format(on="", where=" AND c_acctbal < 2000 AND l_suppkey <> 22"))
_add("filter_nullify", _two, "c o b s", _W6SQL.format(on=" AND l_suppkey <> 22", where=" AND c_acctbal < 2000"), filter_semantics="nullify_owner")
_add("filter_disj", Filter(_W6, "b < 2000 OR s = 22", frozenset({"b", "s"})), "c o b s", _W6SQL.format(on="", where=" AND (c_acctbal < 2000 OR l_suppkey = 22)"))

_F = pattern("F", "orders", o_orderkey="?o", o_orderstatus="F")
_LS = line("L", None, False, l_orderkey="?o", l_suppkey="?s")
_add("distinct_bmm_path", block(_F, O, _LS), "c s", "SELECT DISTINCT o_custkey c, l_suppkey s FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F'", True)
_add(
    "distinct_hub",
    block(pattern("O", "orders", o_orderkey="?o", o_orderpriority="?pr"), line("P", None, False, l_orderkey="?o", l_partkey="?p"), line("L", None, False, l_orderkey="?o", l_suppkey="?s")),
    "pr p s",
    "SELECT DISTINCT o_orderpriority pr, a.p, b.s FROM orders JOIN (SELECT DISTINCT l_orderkey o, l_partkey p FROM lineitem) a ON a.o = o_orderkey JOIN (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem) b ON b.o = o_orderkey",
    True,
)

_W9 = _opt(block(CN), block(O, line("L", l_orderkey="?o", l_suppkey="?s"), SUPPLIER_N))
_W9SQL = "SELECT {d}{v} FROM customer LEFT JOIN (SELECT * FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey) x ON o_custkey = c_custkey AND s_nationkey = c_nationkey"
_add("two_class", _W9, "c n o s", _W9SQL.format(d="", v="c_custkey c, c_nationkey n, o_orderkey o, l_suppkey s"))
_add(
    "cyclic_core",
    _opt(block(CN, O, line("L", l_orderkey="?o", l_suppkey="?s"), SUPPLIER_N), block(PURCHASES)),
    "c n o s e",
    "SELECT c_custkey c, c_nationkey n, o_orderkey o, l_suppkey s, event_id e FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') x ON user_id = c_custkey",
)
_add(
    "cyclic_child",
    _opt(block(pattern("N", "nation", n_nationkey="?n", n_regionkey=1)), block(pattern("C", "customer", c_custkey="?c", c_nationkey="?n", c_mktsegment="BUILDING"), O, line("L", l_orderkey="?o", l_suppkey="?s"), SUPPLIER_N)),
    "n c o s",
    "SELECT n_nationkey n, c_custkey c, o_orderkey o, l_suppkey s FROM nation LEFT JOIN (SELECT * FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey WHERE c_mktsegment = 'BUILDING') x ON c_nationkey = n_nationkey WHERE n_regionkey = 1",
)
_add(
    "parent_linked",
    _opt(block(C, O), block(PURCHASES, line("L", l_orderkey="?o", l_partkey="?p", l_returnflag="R"))),
    "c o e p",
    """SELECT c_custkey c, o_orderkey o, x.event_id e, x.l_partkey p FROM customer JOIN orders ON o_custkey = c_custkey LEFT JOIN
    (SELECT event_id, user_id, l_orderkey, l_partkey FROM events JOIN orders ON o_custkey = user_id JOIN lineitem ON l_orderkey = o_orderkey WHERE event_type = 'purchase' AND l_returnflag = 'R') x
    ON x.user_id = c_custkey AND x.l_orderkey = o_orderkey""",
)
_add(
    "union_bag",
    Union(
        block(CN, pattern("N", "nation", n_nationkey="?n", n_regionkey=1)),
        Union(block(pattern("C2", "customer", c_custkey="?c"), pattern("O2", "orders", o_orderkey="?o2", o_custkey="?c", o_orderpriority="1-URGENT")), LeftJoin(block(pattern("C3", "customer", c_custkey="?c")), block(PURCHASES))),
    ),
    "c",
    "SELECT c_custkey c FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey = 1 UNION ALL SELECT o_custkey FROM orders JOIN customer ON c_custkey = o_custkey WHERE o_orderpriority = '1-URGENT' UNION ALL SELECT c_custkey FROM customer LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') x ON user_id = c_custkey",
)
_W14 = LeftJoin(block(C), Union(block(pattern("U", "orders", o_orderkey="?x", o_custkey="?c", o_orderpriority="1-URGENT")), block(pattern("V", "events", event_id="?x", user_id="?c", event_type="purchase"))))
_W14SQL = "SELECT {d}c_custkey c, x FROM customer LEFT JOIN (SELECT o_orderkey x, o_custkey k FROM orders WHERE o_orderpriority = '1-URGENT' UNION ALL SELECT event_id, user_id FROM events WHERE event_type = 'purchase') u ON k = c_custkey"
_add("union_flags", _W14, "c x", _W14SQL.format(d=""))
_add("union_min_global", _W14, "c x", _W14SQL.format(d="DISTINCT "), union_scope="global")
_add("distinct_union", _W14, "c x", _W14SQL.format(d="DISTINCT "), True)
_W14E = Union(block(pattern("C1", "customer", c_custkey="?c")), LeftJoin(block(pattern("C2", "customer", c_custkey="?c")), block(pattern("E", "events", event_id="?e", user_id="?c"))))
_add("union_subsumed_kept", _W14E, "c e", "SELECT c_custkey c, NULL::BIGINT e FROM customer UNION ALL SELECT c_custkey, event_id FROM customer LEFT JOIN events ON user_id = c_custkey")

_W15 = _opt(block(O), block(line("L", None, False, l_orderkey="?o", l_suppkey="?s", l_returnflag="R")))
_W15SQL = "SELECT DISTINCT {v} FROM orders LEFT JOIN (SELECT * FROM lineitem WHERE l_returnflag = 'R') ON l_orderkey = o_orderkey"
_add("distinct_optional_case1", _W15, "c s", _W15SQL.format(v="o_custkey c, l_suppkey s"), True)
_add("distinct_optional_case2", _W15, "s", _W15SQL.format(v="l_suppkey s"), True)
_add("distinct_cyclic", _W9, "c s", _W9SQL.format(d="DISTINCT ", v="c_custkey c, l_suppkey s"), True)
_add("distinct_filter", _two, "b s", _W6SQL.format(on="", where=" AND c_acctbal < 2000 AND l_suppkey <> 22").replace("SELECT c_custkey c, o_orderkey o, c_acctbal b", "SELECT DISTINCT c_acctbal b"), True)
_add(
    "docs_labels",
    _opt(block(pattern("D", "documents", doc_id="?d", lang="fr")), block(pattern("B", "labels", doc_id="?d", quality=1, toxic=0))),
    "d ok:B",
    "SELECT documents.doc_id d, x.doc_id IS NOT NULL AS hit FROM documents LEFT JOIN (SELECT * FROM labels WHERE quality = 1 AND toxic = 0) x ON x.doc_id = documents.doc_id WHERE lang = 'fr'",
)
_add(
    "conv_system",
    _opt(block(distinct_pattern("V", "conversations", conv_id="?v")), block(pattern("T", "conversations", conv_id="?v", turn="?t", role="system"))),
    "v t",
    "SELECT v, turn t FROM (SELECT DISTINCT conv_id v FROM conversations) LEFT JOIN (SELECT * FROM conversations WHERE role = 'system') ON conv_id = v",
)

_SEVERAL = LeftJoin(LeftJoin(block(CN), block(pattern("U", "orders", o_orderkey="?o", o_custkey="?c", o_orderpriority="1-URGENT"), line("R", None, False, l_orderkey="?o", l_suppkey="?s", l_returnflag="R"))), block(pattern("V", "events", event_id="?e", user_id="?c", event_type="?t")))
_add(
    "distinct_several",
    _SEVERAL,
    "n s t",
    "SELECT DISTINCT c_nationkey n, l_suppkey s, event_type t FROM customer LEFT JOIN (SELECT * FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderpriority = '1-URGENT' AND l_returnflag = 'R') x ON o_custkey = c_custkey LEFT JOIN events ON user_id = c_custkey",
    True,
)
_add("distinct_skips_child", _SEVERAL, "n t", "SELECT DISTINCT c_nationkey n, event_type t FROM customer LEFT JOIN events ON user_id = c_custkey", True)
_BOTH = Filter(_W6, "b < 2000 AND c > 5", frozenset({"b", "c"}))
_BOTHSQL = _W6SQL.format(on="", where=" AND c_acctbal < 2000 AND c_custkey > 5")
for _place in ("load", "chain"):
    _add(f"filter_{_place}", _BOTH, "c o b s", _BOTHSQL, filter_place=_place)
_add("filter_rule4", _BOTH, "c o b s", _BOTHSQL)
_add(
    "filter_rule5",
    Filter(Union(block(pattern("U", "orders", o_orderkey="?x", o_custkey="?c", o_orderpriority="1-URGENT")), block(pattern("V", "events", event_id="?x", user_id="?c", event_type="purchase"))), "c < 50 OR x > 100", frozenset({"c", "x"})),
    "c x",
    "SELECT * FROM (SELECT o_custkey c, o_orderkey x FROM orders WHERE o_orderpriority = '1-URGENT' UNION ALL SELECT user_id, event_id FROM events WHERE event_type = 'purchase') WHERE c < 50 OR x > 100",
)
_add("union_set", _W14, "c x", _W14SQL.format(d="DISTINCT "), union_scope="set")
_add("union_min_family", _W14, "c x", _W14SQL.format(d="DISTINCT "), union_scope="family")
_URGENT = pattern("U", "orders", o_orderkey="?x", o_custkey="?c", o_orderpriority="1-URGENT")
_VIEW = pattern("W", "events", event_id="?w", user_id="?c", event_type="view")
_ARMS = Union(block(pattern("K", "customer", c_custkey="?c", c_nationkey=7)), block(pattern("M", "customer", c_custkey="?c", c_mktsegment="BUILDING")))
_ARMSQL = "(SELECT c_custkey c FROM customer WHERE c_nationkey = 7 UNION ALL SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')"
_add("union_rule1", LeftJoin(_ARMS, block(_URGENT)), "c x", f"SELECT c, o_orderkey x FROM {_ARMSQL} LEFT JOIN (SELECT * FROM orders WHERE o_orderpriority = '1-URGENT') ON o_custkey = c")
_add("union_rule2", Join(_ARMS, block(_URGENT)), "c x", f"SELECT c, o_orderkey x FROM {_ARMSQL} JOIN orders ON o_custkey = c WHERE o_orderpriority = '1-URGENT'")
_add("union_subsumed_global", Union(block(pattern("C1", "customer", c_custkey="?c")), LeftJoin(block(pattern("C2", "customer", c_custkey="?c")), block(pattern("E", "events", event_id="?e", user_id="?c")))), "c e", "SELECT DISTINCT c_custkey c, event_id e FROM customer LEFT JOIN events ON user_id = c_custkey", union_scope="global")
_add(
    "cyclic_child_nations",
    _opt(block(pattern("N", "nation", n_nationkey="?n")), block(pattern("C", "customer", c_custkey="?c", c_nationkey="?n", c_mktsegment="BUILDING"), pattern("O", "orders", o_orderkey="?o", o_custkey="?c", o_orderpriority="1-URGENT"), line("L", l_orderkey="?o", l_suppkey="?s"), pattern("S", "supplier", "s_acctbal > 6000", s_suppkey="?s", s_nationkey="?n"))),
    "n c o s",
    "SELECT n_nationkey n, c_custkey c, o_orderkey o, l_suppkey s FROM nation LEFT JOIN (SELECT * FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey WHERE c_mktsegment = 'BUILDING' AND o_orderpriority = '1-URGENT' AND s_acctbal > 6000) x ON c_nationkey = n_nationkey",
)
#: Groupings of the first query that give other answers.
_add("regroup_inner", _opt(block(pattern("T1", "customer", c_custkey="?c", c_nationkey=7)), block(O)), "c o", "SELECT c_custkey c, o_orderkey o FROM customer LEFT JOIN orders ON o_custkey = c_custkey WHERE c_nationkey = 7")
_add(
    "regroup_left",
    _opt(_opt(block(pattern("T1", "customer", c_custkey="?c", c_nationkey=7)), block(O)), block(pattern("F", "orders", "o_orderstatus = 'F'", o_orderkey="?o", o_orderstatus="?st"))),
    "c o st",
    "SELECT c_custkey c, a.o_orderkey o, b.o_orderstatus st FROM customer LEFT JOIN orders a ON a.o_custkey = c_custkey LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') b ON b.o_orderkey = a.o_orderkey WHERE c_nationkey = 7",
    plan="nested",  # it isn't well designed, so it is evaluated as written
)
_add(
    "cross_guarded",
    _opt(block(pattern("R", "region", r_regionkey="?r")), block(pattern("N", "nation", n_nationkey="?n"))),
    "r n",
    "SELECT r_regionkey r, n_nationkey n FROM region LEFT JOIN nation ON true",
    on_disconnected="cross",
)
