"""Queries over the triples view, the index layer, the structure of queries, and null semantics."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from pyspark.sql import functions as F

from .. import metrics, workloads
from ..algebra import LeftJoin, Pattern, Query, block
from ..engine import compatible_join, drop_empty_mappings, minimum_union, run
from ..functions import bits
from ..plans import structure as st
from ..sources.tables import Catalog, SliceCatalog, triples, write_slices


def graph_pattern(name: str, s: object, p: str, o: object) -> Pattern:
    """A triple pattern over the registered view."""
    return Pattern(name, "triples", (("s", s), ("p", p), ("o", o)), None, "set")


def with_triples(c: Catalog, *tables: str) -> Catalog:
    return Catalog(c.spark, c.folder, {"triples": triples(c, list(tables) or None)})


def q1(c: Catalog) -> DataFrame:
    query = Query(LeftJoin(block(graph_pattern("T1", "?c", "c_nationkey", "nation/7")), block(graph_pattern("O", "?o", "o_custkey", "?c"), graph_pattern("F", "?o", "o_orderstatus", "F"))), ("c", "o"))
    return run(with_triples(c, "customer", "orders"), query)


def tail(c: Catalog) -> DataFrame:
    """Orders with the suppliers of nation 7 among their lines, through line nodes."""
    query = Query(
        LeftJoin(block(graph_pattern("O", "?o", "o_custkey", "?c")), block(graph_pattern("L", "?l", "l_orderkey", "?o"), graph_pattern("M", "?l", "l_suppkey", "?s"), graph_pattern("S", "?s", "s_nationkey", "nation/7"))),
        ("o", "s"),
    )
    return run(with_triples(c, "orders", "supplier", "lineitem"), query)


def predicate_join(c: Catalog) -> DataFrame:
    """A variable in predicate position: which predicates lead from customers of nation 7 to what."""
    query = Query(block(graph_pattern("T1", "?c", "c_nationkey", "nation/7"), Pattern("A", "triples", (("s", "?c"), ("p", "?p"), ("o", "?o")), None, "set")), ("p",), True)
    return run(with_triples(c, "customer"), query)


_TRIPLES_SQL = "SELECT count(*) n FROM (SELECT c_custkey FROM customer UNION ALL SELECT c_custkey FROM customer UNION ALL SELECT c_custkey FROM customer UNION ALL SELECT c_custkey FROM customer)"


def structure_rows(c: Catalog) -> DataFrame:
    rows = []
    for name in ("q1", "nested6", "composite_acyclic", "two_class", "cyclic_core", "cyclic_child", "parent_linked"):
        nodes = st.block_tree(workloads.QUERIES[name].body)
        names = [p.name for x in nodes for p in x.patterns]
        rows.append((name, len(nodes), st.acyclic(names, st.links(nodes)), st.variable_graph_acyclic([p for x in nodes for p in x.patterns]), st.repair_required(nodes).repair))
    return c.spark.createDataFrame(rows, "query string, blocks int, acyclic boolean, variable_graph_acyclic boolean, repair boolean")


_STRUCTURE_SQL = """SELECT * FROM (VALUES ('q1', 2, true, true, false), ('nested6', 5, true, true, false), ('composite_acyclic', 1, true, false, false), ('two_class', 2, false, false, true),
('cyclic_core', 2, false, false, false), ('cyclic_child', 2, false, false, true), ('parent_linked', 2, true, true, true)) t("query", blocks, acyclic, variable_graph_acyclic, repair)"""


def toy(c: Catalog, **options: object) -> DataFrame:
    rows = [("Jerry", "hasFriend", "Julia"), ("Jerry", "hasFriend", "Larry"), ("Larry", "actedIn", "CurbYourEnthu"), ("Julia", "actedIn", "Seinfeld"), ("Julia", "actedIn", "Veep"), ("Julia", "actedIn", "NewAdvOldChristine"), ("Julia", "actedIn", "CurbYourEnthu"), ("Seinfeld", "location", "NYC")]
    catalog = Catalog(c.spark, None, {"triples": c.spark.createDataFrame(rows, "s string, p string, o string")})
    query = Query(LeftJoin(block(graph_pattern("A", "Jerry", "hasFriend", "?friend")), block(graph_pattern("B", "?friend", "actedIn", "?sitcom"), graph_pattern("D", "?sitcom", "location", "NYC"))), ("friend", "sitcom"))
    return run(catalog, query, **options)


_LEFT_A = "CASE WHEN o_orderstatus <> 'O' AND o_orderkey <> 1 THEN o_custkey END"
_LEFT_B = "CASE WHEN o_orderstatus <> 'F' AND o_orderkey <> 1 THEN o_orderkey END"
_COMPATIBLE_SQL = f"""WITH l AS (SELECT {_LEFT_A} a, {_LEFT_B} b FROM orders), r AS (SELECT o_custkey a, o_orderkey b FROM orders WHERE o_orderpriority = '1-URGENT')
SELECT r.a, r.b FROM l JOIN r ON l.a = r.a AND l.b = r.b UNION ALL SELECT r.a, r.b FROM l JOIN r ON l.a = r.a WHERE l.b IS NULL
UNION ALL SELECT r.a, r.b FROM l JOIN r ON l.b = r.b WHERE l.a IS NULL UNION ALL SELECT r.a, r.b FROM l, r WHERE l.a IS NULL AND l.b IS NULL"""


def null_join(c: Catalog) -> DataFrame:
    """Orders that bind a customer, themselves, both or (one of them) nothing, with the urgent orders they agree with."""
    left = c.table("orders").select(F.expr(_LEFT_A).alias("a"), F.expr(_LEFT_B).alias("b"))
    right = c.table("orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("a"), F.col("o_orderkey").alias("b"))
    return compatible_join(left, right, ["a", "b"])


def null_union(c: Catalog) -> DataFrame:
    """Customers of finished orders beside urgent orders, and users of purchases; rows that bind neither say nothing."""
    orders = c.table("orders").select(F.expr("CASE WHEN o_orderstatus = 'F' THEN o_custkey END").alias("a"), F.expr("CASE WHEN o_orderpriority = '1-URGENT' THEN o_orderkey END").alias("b"))
    users = c.table("events").select(F.expr("CASE WHEN event_type = 'purchase' THEN user_id END").alias("a"), F.lit(None).cast("long").alias("b"))
    return drop_empty_mappings(orders.unionByName(users))


def null_minimum(c: Catalog) -> DataFrame:
    """Customers with their urgent orders; those of the other arms only where they have none."""
    alone = lambda table, key: c.table(table).select(F.col(key).alias("a"), F.lit(None).cast("long").alias("b"))
    urgent = c.table("orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("a"), F.col("o_orderkey").alias("b"))
    return minimum_union([alone("customer", "c_custkey"), urgent, alone("events", "user_id")])


def bits_semijoin(c: Catalog) -> DataFrame:
    lines = c.table("lineitem").select("l_orderkey")
    keys = c.table("orders").filter("o_orderstatus = 'F'").select("o_orderkey")
    return bits.unfold(lines, bits.fold_bits(keys, "o_orderkey"), "l_orderkey").agg(F.count("*").alias("n"))


def bits_and(c: Catalog) -> DataFrame:
    a = bits.fold_bits(c.table("orders").filter("o_orderpriority = '1-URGENT'"), "o_custkey")
    b = bits.fold_bits(c.table("events").filter("event_type = 'purchase'"), "user_id")
    return bits.popcount(bits.mask_and(a, b))


def dictionary(c: Catalog) -> DataFrame:
    """Terms by class: subject and object, or one side."""
    t = triples(c, ["nation", "customer", "region"])
    return term_classes(t).groupBy("dim").agg(F.count("*").alias("n"))


def term_classes(t: DataFrame) -> DataFrame:
    """(term, dim): every subject and object once; dim is so, s or o."""
    s, o = t.select(F.col("s").alias("term")).distinct().withColumn("is_s", F.lit(1)), t.select(F.col("o").alias("term")).distinct().withColumn("is_o", F.lit(1))
    return s.join(o, "term", "full").select("term", F.when(F.col("is_s").isNull(), "o").when(F.col("is_o").isNull(), "s").otherwise("so").alias("dim"))


_DICT_SQL = """WITH s AS (SELECT 'nation/' || n_nationkey t FROM nation UNION SELECT 'customer/' || c_custkey FROM customer UNION SELECT 'region/' || r_regionkey FROM region),
o AS (SELECT 'region/' || n_regionkey t FROM nation UNION SELECT n_name FROM nation UNION SELECT 'nation/' || c_nationkey FROM customer UNION SELECT c_name FROM customer UNION SELECT c_acctbal::varchar FROM customer UNION SELECT c_mktsegment FROM customer UNION SELECT r_name FROM region)
SELECT CASE WHEN s.t IS NULL THEN 'o' WHEN o.t IS NULL THEN 's' ELSE 'so' END AS dim, count(*) n FROM s FULL JOIN o ON s.t = o.t GROUP BY 1"""


def ranks(df: DataFrame, groups: list[str], value: str) -> DataFrame:
    """df's distinct rows with `rank`, 1..n in each group in the order of the values, without a window over a whole group.

    Rows are dealt into ranges once; how many rows of each group a range holds gives the offset of the next.
    """
    from pyspark.sql import Window

    from ..lineage import checkpointed

    keys = [*groups, value]
    ordered = df.select(*keys).distinct().repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_part", F.spark_partition_id())
    ordered = checkpointed(ordered)
    counts = ordered.groupBy("_part", *groups).agg(F.count("*").alias("n"))  # a row for each range and group
    before = Window.partitionBy(*groups).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    start = counts.select("_part", *groups, F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_start"))
    rank = F.row_number().over(Window.partitionBy("_part", *groups).orderBy(value))
    return ordered.join(start, ["_part", *groups]).select(*keys, (F.col("_start") + rank).alias("rank"))


def dense_ids(df: DataFrame, value: str) -> DataFrame:
    """(value, id): ids 1..n in the order of the values."""
    return ranks(df.withColumn("_all", F.lit(0)), ["_all"], value).select(value, F.col("rank").alias("id"))


def dictionary_ids(t: DataFrame) -> DataFrame:
    """(term, dim, id) of all triples. Terms that are subject and object come first, so such a term has one id on both
    sides; subjects alone and objects alone follow, each from the next id on. Predicates are numbered by themselves."""
    classes = term_classes(t).unionByName(t.select(F.col("p").alias("term"), F.lit("p").alias("dim")).distinct())
    numbered = ranks(classes, ["dim"], "term")
    shared = classes.filter("dim = 'so'").agg(F.count("*").alias("_n"))
    return numbered.crossJoin(F.broadcast(shared)).select("term", "dim", (F.col("rank") + F.when(F.col("dim").isin("s", "o"), F.col("_n")).otherwise(0)).alias("id"))


def encode(t: DataFrame, ids: DataFrame) -> DataFrame:
    """The triples as ids (s, p, o)."""
    side = lambda name, dims: ids.filter(F.col("dim").isin(*dims)).select(F.col("term").alias(name), F.col("id").alias(f"_{name}"))
    out = t.select("s", "p", "o").join(side("s", ("so", "s")), "s").join(side("o", ("so", "o")), "o").join(F.broadcast(side("p", ("p",))), "p")
    return out.select(*(F.col(f"_{x}").alias(x) for x in "spo"))


_PLAIN = ["region", "nation", "customer", "supplier", "orders"]
_TRIPLE_SQL = """SELECT 'region/' || r_regionkey s, 'r_name' p, r_name o FROM region UNION SELECT 'nation/' || n_nationkey, 'n_regionkey', 'region/' || n_regionkey FROM nation
UNION SELECT 'nation/' || n_nationkey, 'n_name', n_name FROM nation UNION SELECT 'customer/' || c_custkey, 'c_nationkey', 'nation/' || c_nationkey FROM customer
UNION SELECT 'customer/' || c_custkey, 'c_name', c_name FROM customer UNION SELECT 'customer/' || c_custkey, 'c_acctbal', c_acctbal::VARCHAR FROM customer
UNION SELECT 'customer/' || c_custkey, 'c_mktsegment', c_mktsegment FROM customer UNION SELECT 'supplier/' || s_suppkey, 's_nationkey', 'nation/' || s_nationkey FROM supplier
UNION SELECT 'supplier/' || s_suppkey, 's_name', s_name FROM supplier UNION SELECT 'supplier/' || s_suppkey, 's_acctbal', s_acctbal::VARCHAR FROM supplier
UNION SELECT 'order/' || o_orderkey, 'o_custkey', 'customer/' || o_custkey FROM orders UNION SELECT 'order/' || o_orderkey, 'o_orderstatus', o_orderstatus FROM orders
UNION SELECT 'order/' || o_orderkey, 'o_totalprice', o_totalprice::VARCHAR FROM orders UNION SELECT 'order/' || o_orderkey, 'o_orderpriority', o_orderpriority FROM orders"""
_IDS_SQL = f"""WITH t AS ({_TRIPLE_SQL}), d AS (SELECT coalesce(a.s, b.o) AS term, CASE WHEN a.s IS NULL THEN 'o' WHEN b.o IS NULL THEN 's' ELSE 'so' END AS dim
FROM (SELECT DISTINCT s FROM t) a FULL JOIN (SELECT DISTINCT o FROM t) b ON a.s = b.o UNION ALL SELECT DISTINCT p, 'p' FROM t)
SELECT term, dim, row_number() OVER (PARTITION BY dim ORDER BY term) + CASE WHEN dim IN ('s', 'o') THEN (SELECT count(*) FROM d WHERE dim = 'so') ELSE 0 END AS id FROM d"""


def sliced(c: Catalog) -> DataFrame:
    """The first query over the four clustered copies of the triples, each pattern read from the copy that fits it."""
    from ..lineage import shared_dir

    folder = f"{shared_dir(c.spark)}/slices-{uuid.uuid4().hex}"
    write_slices(triples(c, ["customer", "orders"]), folder, 8)
    query = Query(LeftJoin(block(graph_pattern("T1", "?c", "c_nationkey", "nation/7")), block(graph_pattern("O", "?o", "o_custkey", "?c"), graph_pattern("F", "?o", "o_orderstatus", "F"))), ("c", "o"))
    return run(SliceCatalog(c.spark, folder), query)


OPERATORS = {
    "graph_q1": (q1, "SELECT 'customer/' || c_custkey c, 'order/' || o_orderkey o FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') ON o_custkey = c_custkey WHERE c_nationkey = 7"),
    "graph_tail": (tail, "SELECT 'order/' || o_orderkey o, 'supplier/' || l_suppkey s FROM orders LEFT JOIN (SELECT * FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey = 7) x ON l_orderkey = o_orderkey"),
    "graph_predicate_join": (predicate_join, "SELECT * FROM (VALUES ('c_nationkey'), ('c_name'), ('c_acctbal'), ('c_mktsegment')) t(p)"),
    "graph_triples": (lambda c: triples(c, ["customer"]).agg(F.count("*").alias("n")), _TRIPLES_SQL),
    "graph_q1_slices": (sliced, "SELECT 'customer/' || c_custkey c, 'order/' || o_orderkey o FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') ON o_custkey = c_custkey WHERE c_nationkey = 7"),
    "graph_triples_plain": (lambda c: triples(c, _PLAIN).select("s", "p", "o"), _TRIPLE_SQL),
    "index_dict_ids": (lambda c: dictionary_ids(triples(c, _PLAIN)), _IDS_SQL),
    "index_encoded": (lambda c: (lambda t: encode(t, dictionary_ids(t)))(triples(c, _PLAIN)), f"WITH i AS ({_IDS_SQL}), x AS ({_TRIPLE_SQL}) SELECT a.id s, b.id p, d.id o FROM x JOIN i a ON a.term = x.s AND a.dim IN ('so', 's') JOIN i b ON b.term = x.p AND b.dim = 'p' JOIN i d ON d.term = x.o AND d.dim IN ('so', 'o')"),
    "index_counts_plain": (lambda c: metrics.predicate_stats(triples(c, _PLAIN)), f"SELECT p, count(*) n, count(DISTINCT s) n_s, count(DISTINCT o) n_o FROM ({_TRIPLE_SQL}) GROUP BY p"),
    "index_slices_plain": (lambda c: metrics.slice_count(triples(c, _PLAIN)), f"SELECT 2 * count(DISTINCT p) + count(DISTINCT s) + count(DISTINCT o) AS slices FROM ({_TRIPLE_SQL})"),
    "index_row_codes": (
        lambda c: metrics.row_code_sizes(triples(c, ["orders"]), "o_custkey"),
        """WITH p AS (SELECT o_custkey r, dense_rank() OVER (ORDER BY 'order/' || o_orderkey) AS i FROM (SELECT DISTINCT o_custkey, o_orderkey FROM orders)),
        m AS (SELECT r, i, (i - lag(i) OVER (PARTITION BY r ORDER BY i) IS DISTINCT FROM 1)::INT AS fresh FROM p),
        k AS (SELECT count(*) k, sum(fresh) * 2 + (min(i) > 1)::INT + (max(i) < (SELECT max(i) FROM p))::INT AS runs FROM m GROUP BY r)
        SELECT sum(runs)::BIGINT AS runs, sum(CASE WHEN k < runs - 1 THEN k ELSE runs END)::BIGINT AS hybrid FROM k""",
    ),
    "index_fold": (lambda c: bits.positions(bits.fold_bits(c.table("orders").filter("o_orderstatus = 'F'"), "o_custkey"), "o_custkey"), "SELECT DISTINCT o_custkey FROM orders WHERE o_orderstatus = 'F'"),
    "index_unfold": (lambda c: bits.unfold(c.table("customer").select("c_custkey"), bits.fold_bits(c.table("events").filter("event_type = 'purchase'"), "user_id"), "c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events WHERE event_type = 'purchase')"),
    "null_subsume": (
        lambda c: minimum_union([c.table("customer").select(F.col("c_custkey").alias("c"), F.lit(None).cast("long").alias("e")), c.table("events").select(F.col("user_id").alias("c"), F.col("event_id").alias("e"))]),
        "WITH u AS (SELECT c_custkey c, NULL::BIGINT e FROM customer UNION SELECT user_id, event_id FROM events) SELECT c, e FROM u a WHERE NOT EXISTS (SELECT 1 FROM u b WHERE (a.c IS NULL OR a.c = b.c) AND (a.e IS NULL OR a.e = b.e) AND (a.c IS NULL)::INT + (a.e IS NULL)::INT > (b.c IS NULL)::INT + (b.e IS NULL)::INT)",
    ),
    "structure_costs": (
        lambda c: metrics.structure_costs(c, {k: workloads.QUERIES[k] for k in ("q1", "composite_acyclic", "two_class", "q2_union", "union_bag")}),
        "SELECT * FROM (VALUES ('q1', 3, 4, 3, 1), ('composite_acyclic', 4, 9, 6, 1), ('two_class', 4, 9, 6, 1), ('q2_union', 6, 10, 0, 2), ('union_bag', 6, 9, 0, 3)) t(\"query\", patterns, cells, semijoins, arms)",
    ),
    "index_counts": (lambda c: metrics.predicate_stats(triples(c, ["nation"])), "SELECT 'n_regionkey' p, count(*) n, count(DISTINCT n_nationkey) n_s, count(DISTINCT n_regionkey) n_o FROM nation UNION ALL SELECT 'n_name', count(*), count(DISTINCT n_nationkey), count(DISTINCT n_name) FROM nation"),
    "index_slices": (lambda c: metrics.slice_count(triples(c, ["nation"])), "SELECT 2 * 2 + (SELECT count(*) FROM nation) + (SELECT count(DISTINCT n_regionkey) FROM nation) + (SELECT count(DISTINCT n_name) FROM nation) AS slices"),
    "index_dict": (dictionary, _DICT_SQL),
    "index_dense_ids": (lambda c: dense_ids(c.table("customer"), "c_name"), "SELECT c_name, dense_rank() OVER (ORDER BY c_name) AS id FROM (SELECT DISTINCT c_name FROM customer)"),
    "index_semijoin_bits": (bits_semijoin, "SELECT count(*) n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')"),
    "index_mask_and": (bits_and, "SELECT count(*)::BIGINT n FROM (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT' INTERSECT SELECT user_id FROM events WHERE event_type = 'purchase')"),
    "index_hybrid": (lambda c: metrics.row_code_sizes(triples(c, ["orders"]), "o_custkey", "s", "o"), "SELECT sum(CASE WHEN r IN (1, n) THEN 3 ELSE 4 END)::BIGINT AS runs, count(*)::BIGINT AS hybrid FROM (SELECT dense_rank() OVER (ORDER BY 'customer/' || o_custkey) r, (SELECT count(DISTINCT o_custkey) FROM orders) n FROM orders)"),
    "structure_decisions": (structure_rows, _STRUCTURE_SQL),
    "toy_graph": (toy, "SELECT * FROM (VALUES ('Julia', 'Seinfeld'), ('Larry', NULL)) t(friend, sitcom)"),
    "toy_graph_repaired": (lambda c: toy(c, reduce="off", force_repair=True), "SELECT * FROM (VALUES ('Julia', 'Seinfeld'), ('Larry', NULL)) t(friend, sitcom)"),
    "null_compat_join": (null_join, _COMPATIBLE_SQL),
    "null_empty_mapping": (
        null_union,
        "SELECT CASE WHEN o_orderstatus = 'F' THEN o_custkey END a, CASE WHEN o_orderpriority = '1-URGENT' THEN o_orderkey END b FROM orders WHERE o_orderstatus = 'F' OR o_orderpriority = '1-URGENT' UNION ALL SELECT user_id, NULL FROM events WHERE event_type = 'purchase' AND user_id IS NOT NULL",
    ),
    "null_minimum_union": (
        null_minimum,
        "WITH u AS (SELECT DISTINCT o_custkey a, o_orderkey b FROM orders WHERE o_orderpriority = '1-URGENT') SELECT * FROM u UNION ALL SELECT a, NULL FROM (SELECT c_custkey a FROM customer UNION SELECT user_id FROM events) x WHERE NOT EXISTS (SELECT 1 FROM u WHERE u.a = x.a)",
    ),
}
