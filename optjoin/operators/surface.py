"""Query texts, files, functions in Python form and observed metrics as registered queries."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import metrics, workloads
from ..engine import bind, block_flags, chain_join, nullify, run
from ..functions import bits, udfs
from ..lineage import shared_dir
from ..parser import evaluate
from ..plans import structure as st
from ..sources import files
from ..sources.tables import Catalog, triples, write_triples
from .graph import OPERATORS as GRAPH_OPERATORS
from .graph import with_triples


def _folder(c: Catalog) -> str:
    return f"{shared_dir(c.spark)}/files-{uuid.uuid4().hex}"


def _text(query: str):
    return lambda c: evaluate(c, query)


def lines(c: Catalog) -> DataFrame:
    folder = _folder(c)
    files.write_nt(triples(c, ["nation", "part"]), folder, F.col("p") == "n_regionkey")
    return files.read_nt(c.spark, folder).groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("o").alias("n_o"))


def again(fmt: str):
    def query(c: Catalog) -> DataFrame:
        folder, region = _folder(c), c.table("region").select("r_regionkey", "r_name")
        files.write_any(region, folder, fmt)
        return files.read_any(c.spark, folder, fmt, region.schema)

    return query


def partitioned(c: Catalog) -> DataFrame:
    folder = _folder(c)
    write_triples(triples(c, ["customer"]), folder)
    return c.spark.read.parquet(folder).filter("p = 'c_nationkey'").groupBy("o").agg(F.count("*").alias("n"))


def bucketed(c: Catalog) -> DataFrame:
    table = files.write_bucketed(c.table("lineitem").select("l_orderkey", "l_linenumber"), f"lines_{uuid.uuid4().hex}", "l_orderkey", 8, _folder(c))
    return table.groupBy("l_orderkey").agg(F.count("*").alias("n"))


def row_codes(c: Catalog) -> DataFrame:
    """Each customer's orders by key as bits (whether urgent), in the hybrid code."""
    bit = F.when(F.col("o_orderpriority") == "1-URGENT", "1").otherwise("0")
    rows = c.table("orders").groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.struct("o_orderkey", bit.alias("b")))).alias("x"))
    return rows.select("o_custkey", udfs.encode_row_udf()(F.array_join("x.b", "")).alias("code"))


def runs(c: Catalog) -> DataFrame:
    return c.table("lineitem").groupBy("l_orderkey").agg(udfs.rle_agg()(F.col("l_linenumber")).alias("runs"))


def table_function(c: Catalog) -> DataFrame:
    udfs.register_functions(c.spark)
    view = f"rows_{uuid.uuid4().hex}"
    c.table("nation").createOrReplaceTempView(view)
    return c.spark.sql(f"SELECT t.* FROM {view}, LATERAL row_to_triples(concat('nation/', n_nationkey), array('n_name', 'n_regionkey'), array(n_name, concat('region/', n_regionkey))) t")


def decoded(c: Catalog) -> DataFrame:
    udfs.register_functions(c.spark)
    view = f"mask_{uuid.uuid4().hex}"
    bits.fold_bits(c.table("orders").filter("o_orderstatus = 'F'"), "o_custkey").createOrReplaceTempView(view)
    return c.spark.sql(f"SELECT t.value AS o_custkey FROM {view}, LATERAL decode_positions(bucket, bits) t")


def grouped(c: Catalog) -> DataFrame:
    query = workloads.QUERIES["two_class"]
    nodes = st.block_tree(query.body)
    frames = {p.name: bind(c, p) for x in nodes for p in x.patterns}
    chain = chain_join(frames, nodes, st.chain_order(nodes, {}))
    rows = nullify(block_flags(chain, nodes), nodes)
    rows = rows.drop(*(x for x in rows.columns if x.startswith("_ok_")))
    return udfs.bestmatch_group(rows, sorted(nodes[0].vars)).select(*query.select)


def observed(c: Catalog) -> DataFrame:
    df, seen = metrics.observe(run(c, workloads.QUERIES["q1"]), misses=F.count_if(F.col("o").isNull()))
    df.write.format("noop").mode("overwrite").save()
    return c.spark.createDataFrame([(seen.get["rows"], seen.get["misses"])], "n long, misses long")


OPERATORS = {
    "parse_q1": (_text('SELECT ?c ?o WHERE { customer(c_custkey: ?c, c_nationkey: 7) . OPTIONAL { orders(o_orderkey: ?o, o_custkey: ?c) . orders(o_orderkey: ?o, o_orderstatus: "F") } }'), workloads.SQL["q1"]),
    "parse_graph_q1": (lambda c: evaluate(with_triples(c, "customer", "orders"), 'SELECT ?c ?o { ?c <c_nationkey> <nation/7> . OPTIONAL { ?o <o_custkey> ?c . ?o <o_orderstatus> "F" } }'), GRAPH_OPERATORS["graph_q1"][1]),
    "parse_union": (_text('SELECT ?c ?x { customer(c_custkey: ?c) OPTIONAL { { orders(o_orderkey: ?x, o_custkey: ?c, o_orderpriority: "1-URGENT") } UNION { events(event_id: ?x, user_id: ?c, event_type: "purchase") } } }'), workloads.SQL["union_flags"]),
    "parse_page": (_text("SELECT ?o ?b { orders(o_orderkey: ?o, o_totalprice: ?b) FILTER(?b > 1000 && !(?b >= 50000)) } ORDER BY DESC(?b) ?o LIMIT 20 OFFSET 5"), "SELECT o_orderkey o, o_totalprice b FROM orders WHERE o_totalprice > 1000 AND o_totalprice < 50000 ORDER BY b DESC, o LIMIT 20 OFFSET 5"),
    "parse_distinct": (_text('SELECT DISTINCT ?c ?s { orders(o_orderkey: ?o, o_orderstatus: "F") . orders(o_orderkey: ?o, o_custkey: ?c) . lineitem(l_orderkey: ?o, l_suppkey: ?s) }'), workloads.SQL["distinct_bmm_path"]),
    "parse_bind": (
        _text('SELECT ?c ?k ?twice { customer(c_custkey: ?c, c_acctbal: ?b) OPTIONAL { orders(o_orderkey: ?o, o_custkey: ?c, o_orderpriority: "1-URGENT") } BIND(coalesce(?o, 0) + ?c AS ?k) BIND(2 * ?k AS ?twice) FILTER(?b > 1000) }'),
        "SELECT c_custkey c, coalesce(o_orderkey, 0) + c_custkey k, 2 * k AS twice FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderpriority = '1-URGENT') ON o_custkey = c_custkey WHERE c_acctbal > 1000",
    ),
    "parse_bind_distinct": (
        _text('SELECT DISTINCT ?big ?s { orders(o_orderkey: ?o, o_totalprice: ?p, o_orderstatus: ?s) BIND(?p > 100000 AS ?big) }'),
        "SELECT DISTINCT o_totalprice > 100000 AS big, o_orderstatus s FROM orders",
    ),
    "parse_ask": (_text("ASK { customer(c_custkey: ?c, c_nationkey: 7) . orders(o_orderkey: ?o, o_custkey: ?c) }"), "SELECT count(*) > 0 AS found FROM customer JOIN orders ON o_custkey = c_custkey WHERE c_nationkey = 7"),
    "parse_construct": (
        _text('CONSTRUCT { ?c <of> ?n . ?c <ordered> ?o } WHERE { customer(c_custkey: ?c, c_nationkey: ?n) OPTIONAL { orders(o_orderkey: ?o, o_custkey: ?c, o_orderpriority: "1-URGENT") } }'),
        "SELECT c_custkey::VARCHAR s, 'of' p, c_nationkey::VARCHAR o FROM customer UNION SELECT o_custkey::VARCHAR, 'ordered', o_orderkey::VARCHAR FROM orders JOIN customer ON c_custkey = o_custkey WHERE o_orderpriority = '1-URGENT'",
    ),
    "op_o04_lines": (
        lines,
        """SELECT 'n_name' p, count(*) n, count(DISTINCT n_name) n_o FROM nation UNION ALL SELECT 'n_regionkey', count(*), count(DISTINCT n_regionkey) FROM nation
    UNION ALL SELECT 'p_name', count(*), count(DISTINCT p_name) FROM part UNION ALL SELECT 'p_brand', count(*), count(DISTINCT p_brand) FROM part UNION ALL SELECT 'p_type', count(*), count(DISTINCT p_type) FROM part
    UNION ALL SELECT 'p_size', count(*), count(DISTINCT p_size) FROM part UNION ALL SELECT 'p_retailprice', count(*), count(DISTINCT p_retailprice) FROM part""",
    ),
    **{f"op_o05_{fmt}": (again(fmt), "SELECT r_regionkey, r_name FROM region") for fmt in ("csv", "json", "orc")},
    "op_o08_partitioned": (partitioned, "SELECT 'nation/' || c_nationkey o, count(*) n FROM customer GROUP BY 1"),
    "op_o09_bucketed": (bucketed, "SELECT l_orderkey, count(*) n FROM lineitem GROUP BY 1"),
    "op_o81_row_code": (row_codes, None),
    "op_o82_runs": (runs, "SELECT l_orderkey, count(*) FILTER (fresh)::INT runs FROM (SELECT l_orderkey, l_linenumber - coalesce(lag(l_linenumber) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber), -9) <> 1 AS fresh FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)) GROUP BY 1"),
    "op_o83_table_function": (table_function, "SELECT 'nation/' || n_nationkey s, 'n_name' p, n_name o FROM nation UNION ALL SELECT 'nation/' || n_nationkey, 'n_regionkey', 'region/' || n_regionkey FROM nation"),
    "op_o83_decoded": (decoded, "SELECT DISTINCT o_custkey FROM orders WHERE o_orderstatus = 'F'"),
    "bestmatch_group_two_class": (grouped, workloads.SQL["two_class"]),
    "op_o87_observed": (observed, f"SELECT count(*) n, count(*) - count(o) misses FROM ({workloads.SQL['q1']})"),
}
