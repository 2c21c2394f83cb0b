"""Operators that users of the methods need around them; one entry is one operator and its SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import Catalog


def interval_join(left: DataFrame, right: DataFrame, on: list[str], at: str, other: str, reach: int) -> DataFrame:
    """Pairs with 0 < other - at <= reach (numbers): time is cut into buckets, so the join is by equality."""
    a = left.withColumn("_b", F.explode(F.array(F.floor(F.col(at) / reach), F.floor(F.col(at) / reach) + 1)))
    b = right.withColumn("_b", F.floor(F.col(other) / reach))
    return a.join(b, [*on, "_b"]).filter((F.col(other) > F.col(at)) & (F.col(other) - F.col(at) <= reach)).drop("_b")


def asof(df: DataFrame, by: str, order: list[str], flag, value: str) -> DataFrame:
    """The value of the latest earlier row that satisfies the flag, per key: one window, no self-join."""
    w = Window.partitionBy(by).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn("found", F.last(F.when(flag, F.col(value)), ignorenulls=True).over(w))


def top_per_key(df: DataFrame, key: str, order: list, k: int) -> DataFrame:
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(key).orderBy(*order))).filter(F.col("_n") <= k).drop("_n")


def salted_count(df: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Counts of a skewed key in two steps."""
    return df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_s")).count().groupBy(key).agg(F.sum("count").alias("n"))


def cross(left: DataFrame, right: DataFrame, allow: bool = False) -> DataFrame:
    if not allow:
        raise ValueError("a Cartesian product must be allowed")
    return left.crossJoin(right)


def held_bytes(df: DataFrame) -> int:
    """Bytes of df's rows in a hash table, counted in one scan: those of texts and nested values, and 8 a column and 24 a row beside them."""
    varied = [c for c, kind in df.dtypes if kind == "binary" or kind.startswith(("string", "varchar", "char", "array", "map", "struct", "variant"))]
    size = sum((F.coalesce(F.octet_length(F.col(f"`{c}`").cast("string")), F.lit(0)).cast("long") for c in varied), F.lit(24 + 8 * len(df.columns)).cast("long"))
    return int(df.agg(F.sum(size)).first()[0] or 0)


def broadcast_join(left: DataFrame, right: DataFrame, on: Column, limit: int) -> DataFrame:
    """Inner join that sends the smaller side to all executors, if its rows take at most `limit` bytes there.

    A side that doesn't fit isn't sent: the driver would have to hold it. Then both sides are dealt by key and merged, which
    gives the same rows at any size.
    """
    size, small = min(((held_bytes(df), i) for i, df in enumerate((left, right))))
    if size > limit:
        return left.join(right.hint("merge"), on)
    return left.join(F.broadcast(right), on) if small else F.broadcast(left).join(right, on)


def _t(name: str):
    return lambda c: c.table(name)


def _secs(c: Catalog) -> DataFrame:
    return c.table("events").select("event_id", "user_id", "event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("sec"))


def _joined(hint: str):
    return lambda c: c.table("orders").join(c.table("lineitem").hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


def _broadcast(c: Catalog) -> DataFrame:
    from ..engine import broadcast_limit

    orders, lines = c.table("orders").select("o_orderkey", "o_orderstatus"), c.table("lineitem").select("l_orderkey")
    return broadcast_join(orders, lines, F.col("o_orderkey") == F.col("l_orderkey"), broadcast_limit(c)).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


_JOINED = "SELECT o_orderstatus, count(*) n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _orders_w():
    return Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")


def _events_w():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


def _properties(c: Catalog) -> DataFrame:
    from ..sources.tables import triples

    t = triples(c, ["customer"])
    return t.groupBy("s").pivot("p", ["c_mktsegment", "c_nationkey"]).agg(F.first("o"))


def star(triples_: DataFrame, predicates: dict[str, str]) -> DataFrame:
    """One row per subject that has all these predicates; named by the values of the dict. Bucketed by s, no join shuffles."""
    parts = [triples_.filter(F.col("p") == p).select("s", F.col("o").alias(name)) for p, name in predicates.items()]
    out = parts[0]
    for x in parts[1:]:
        out = out.join(x, "s")
    return out


def to_map(triples_: DataFrame) -> DataFrame:
    """(s, properties): a map of each subject's predicates, ascending; a predicate with several objects has the least."""
    least = triples_.groupBy("s", "p").agg(F.min("o").alias("o"))
    return least.groupBy("s").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("p", "o")))).alias("properties"))


def _triples(*tables: str):
    from ..sources.tables import triples

    return lambda c: triples(c, list(tables) or None)


def _bound(c: Catalog, bound: bool) -> DataFrame:
    from ..engine import run
    from ..workloads import QUERIES

    return run(c, QUERIES["q1"]).filter(F.col("o").isNotNull() if bound else F.col("o").isNull())


def _q1_sql() -> str:
    from ..workloads import SQL

    return SQL["q1"]


OPERATORS = {
    "op_o12_named_graph": (lambda c: _triples("region", "nation")(c).filter("g = 'nation'").select("s", "p", "o"), "SELECT 'nation/' || n_nationkey s, 'n_name' p, n_name o FROM nation UNION ALL SELECT 'nation/' || n_nationkey, 'n_regionkey', 'region/' || n_regionkey FROM nation"),
    "op_o13_project": (lambda c: c.table("customer").select("c_custkey", "c_nationkey", "c_name").withColumnsRenamed({"c_custkey": "c", "c_nationkey": "n"}).drop("c_name"), "SELECT c_custkey c, c_nationkey n FROM customer"),
    "op_o18_bound": (lambda c: _bound(c, True), f"SELECT * FROM ({_q1_sql()}) WHERE o IS NOT NULL"),
    "op_o18_not_bound": (lambda c: _bound(c, False), f"SELECT * FROM ({_q1_sql()}) WHERE o IS NULL"),
    "op_o21_strings_more": (
        lambda c: c.table("part").select("p_partkey", F.lower("p_name").alias("low"), F.concat_ws("/", "p_brand", "p_type").alias("pair"), F.size(F.split("p_name", " ")).alias("parts"), F.trim(F.concat(F.lit("  "), "p_brand", F.lit(" "))).alias("cut"), F.regexp_extract("p_brand", r"(\d+)", 1).alias("number"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("masked")),
        r"SELECT p_partkey, lower(p_name) low, concat_ws('/', p_brand, p_type) pair, len(string_split(p_name, ' '))::INT parts, trim('  ' || p_brand || ' ') cut, regexp_extract(p_brand, '(\d+)', 1) number, regexp_replace(p_type, '[AEIOU]', '_', 'g') masked FROM part",
    ),
    "op_o21_url": (lambda c: c.table("pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host")), "SELECT page_id, nullif(regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1), '') AS host FROM pages"),
    "op_o22_dates_more": (
        lambda c: c.table("orders").select("o_orderkey", F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM-dd").alias("month"), F.date_format(F.date_add(F.to_date("o_orderdate"), 30), "yyyy-MM-dd").alias("due"), F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date")).alias("days")),
        "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, strftime(o_orderdate::DATE + 30, '%Y-%m-%d') AS due, datediff('day', DATE '1990-01-01', o_orderdate::DATE)::INT AS days FROM orders",
    ),
    "op_o23_math_more": (
        lambda c: c.table("lineitem").select("l_orderkey", "l_linenumber", F.ceil("l_quantity").alias("up"), F.abs(F.col("l_orderkey") - 100).alias("off"), F.round(F.sqrt("l_quantity"), 6).alias("root"), F.round(F.pow("l_discount", F.lit(2)), 6).alias("square")),
        "SELECT l_orderkey, l_linenumber, ceil(l_quantity)::BIGINT up, abs(l_orderkey - 100) off, round(sqrt(l_quantity), 6) root, round(pow(l_discount, 2), 6) square FROM lineitem",
    ),
    "op_o25_json_more": (lambda c: c.table("events").select("event_id", F.get_json_object("props", "$.k").alias("text"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")), "SELECT event_id, props->>'$.k' AS text, (props->>'$.k')::INT AS k FROM events"),
    "op_o26_vectors_more": (
        lambda c: c.table("embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x"), F.transform("embedding", lambda x: x.cast("double") * 2)[0].alias("twice"), F.aggregate(F.zip_with("embedding", F.reverse("embedding"), lambda a, b: (a > b).cast("int")), F.lit(0), lambda a, b: a + b).alias("wins")).filter("i < 2").select("vec_id", "i", F.round(F.col("x").cast("double"), 4).alias("x"), F.round("twice", 4).alias("twice"), "wins"),
        "SELECT vec_id, i::INT AS i, round(embedding[i + 1]::DOUBLE, 4) AS x, round(embedding[1]::DOUBLE * 2, 4) AS twice, list_sum([CASE WHEN embedding[j] > embedding[len(embedding) + 1 - j] THEN 1 ELSE 0 END for j in range(1, len(embedding) + 1)])::INT AS wins FROM embeddings, (VALUES (0), (1)) t(i)",
    ),
    "op_o27_map": (lambda c: to_map(_triples("customer")(c)).select("s", F.size("properties").alias("n"), F.element_at("properties", "c_name").alias("name"), F.array_join(F.map_keys("properties"), ",").alias("keys")), "SELECT 'customer/' || c_custkey s, 4 AS n, c_name AS name, 'c_acctbal,c_mktsegment,c_name,c_nationkey' AS keys FROM customer"),
    "op_o28_typed_literals": (lambda c: _triples("customer", "part")(c).groupBy("p").agg(F.count(F.expr("try_cast(o AS double)")).alias("numbers"), F.count("*").alias("n")), """SELECT p, count(try_cast(o AS DOUBLE)) AS numbers, count(*) n FROM (
        SELECT 'c_nationkey' p, 'nation/' || c_nationkey o FROM customer UNION ALL SELECT 'c_name', c_name FROM customer UNION ALL SELECT 'c_acctbal', c_acctbal::VARCHAR FROM customer UNION ALL SELECT 'c_mktsegment', c_mktsegment FROM customer
        UNION ALL SELECT 'p_name', p_name FROM part UNION ALL SELECT 'p_brand', p_brand FROM part UNION ALL SELECT 'p_type', p_type FROM part UNION ALL SELECT 'p_size', p_size::VARCHAR FROM part UNION ALL SELECT 'p_retailprice', p_retailprice::VARCHAR FROM part) GROUP BY p"""),
    "op_o42_star": (lambda c: star(_triples("customer")(c), {"c_nationkey": "n", "c_mktsegment": "m", "c_name": "name"}), "SELECT 'customer/' || c_custkey s, 'nation/' || c_nationkey n, c_mktsegment m, c_name AS name FROM customer"),
    "op_o46_sort_aggregate": (lambda c: c.table("orders").groupBy("o_custkey").agg(F.max("o_orderpriority").alias("last"), F.min("o_orderstatus").alias("least")), "SELECT o_custkey, max(o_orderpriority) AS last, min(o_orderstatus) AS least FROM orders GROUP BY 1"),
    "op_o52_grouping_sets": (lambda c: c.table("lineitem").groupingSets([("l_returnflag", "l_linestatus"), ("l_returnflag",), ()], "l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g, count(*) n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())"),
    "op_o54_unpivot": (lambda c: c.table("nation").select("n_nationkey", "n_regionkey", (F.col("n_nationkey") * 2).alias("twice")).unpivot("n_nationkey", ["n_regionkey", "twice"], "name", "value"), "SELECT n_nationkey, 'n_regionkey' AS name, n_regionkey AS value FROM nation UNION ALL SELECT n_nationkey, 'twice', n_nationkey * 2 FROM nation"),
    "op_o60_order_nulls": (lambda c: c.table("customer").join(c.table("events"), F.col("c_custkey") == F.col("user_id"), "left").select("c_custkey", "event_id").orderBy(F.col("event_id").desc_nulls_first(), "c_custkey").limit(100), "SELECT c_custkey, event_id FROM customer LEFT JOIN events ON c_custkey = user_id ORDER BY event_id DESC NULLS FIRST, c_custkey LIMIT 100"),
    "op_o68_intersect_all": (lambda c: c.table("orders").select("o_custkey").intersectAll(c.table("events").select("user_id")), "SELECT o_custkey FROM orders INTERSECT ALL SELECT user_id FROM events"),
    "op_o69_except_all": (lambda c: c.table("orders").select("o_custkey").exceptAll(c.table("events").select("user_id")), "SELECT o_custkey FROM orders EXCEPT ALL SELECT user_id FROM events"),
    "op_o01_scan": (lambda c: c.table("nation").select("n_nationkey", "n_name"), "SELECT n_nationkey, n_name FROM nation"),
    "op_o03_properties": (_properties, "SELECT 'customer/' || c_custkey s, c_mktsegment, 'nation/' || c_nationkey AS c_nationkey FROM customer"),
    "op_o06_values": (
        lambda c: c.table("orders").join(F.broadcast(c.spark.createDataFrame([("1-URGENT", 1), ("2-HIGH", None)], "x string, y int")), F.col("o_orderpriority") == F.col("x")).select("o_orderkey", "x", "y"),
        "SELECT o_orderkey, x, y FROM orders JOIN (VALUES ('1-URGENT', 1), ('2-HIGH', NULL)) t(x, y) ON o_orderpriority = x",
    ),
    "op_o10_construct": (
        lambda c: c.table("customer").filter("c_nationkey = 7").select(F.concat(F.lit("customer/"), "c_custkey").alias("s"), F.expr("stack(2, 'name', c_name, 'segment', c_mktsegment) AS (p, o)")),
        "SELECT 'customer/' || c_custkey s, 'name' p, c_name o FROM customer WHERE c_nationkey = 7 UNION ALL SELECT 'customer/' || c_custkey, 'segment', c_mktsegment FROM customer WHERE c_nationkey = 7",
    ),
    "op_o11_ask": (lambda c: c.table("customer").filter("c_nationkey = 7").limit(1).agg((F.count("*") > 0).alias("found")), "SELECT count(*) > 0 AS found FROM customer WHERE c_nationkey = 7"),
    "op_o14_computed": (lambda c: c.table("lineitem").select("l_orderkey", F.floor(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue")), "SELECT l_orderkey, floor(l_extendedprice * (1 - l_discount))::BIGINT AS revenue FROM lineitem"),
    "op_o15_where": (lambda c: c.table("customer").filter("c_acctbal < 2000").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_acctbal < 2000"),
    "op_o16_like": (lambda c: c.table("part").filter(F.col("p_name").like("%a%") & F.col("p_brand").rlike("[12]$")).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_brand, '[12]$')"),
    "op_o17_in_between": (lambda c: c.table("orders").filter(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 50000)).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 50000"),
    "op_o20_case": (lambda c: c.table("customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("level")), "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS level FROM customer"),
    "op_o21_strings": (lambda c: c.table("part").select("p_partkey", F.upper("p_name").alias("u"), F.substring("p_type", 1, 4).alias("t"), F.length("p_name").alias("n")), "SELECT p_partkey, upper(p_name) u, substr(p_type, 1, 4) t, length(p_name)::INT n FROM part"),
    "op_o22_dates": (lambda c: c.table("orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n")), "SELECT year(o_orderdate)::INT y, month(o_orderdate)::INT m, count(*) n FROM orders GROUP BY 1, 2"),
    "op_o23_math": (lambda c: c.table("lineitem").select("l_orderkey", F.floor("l_quantity").alias("f"), F.pmod(F.col("l_orderkey"), F.lit(7)).alias("k")), "SELECT l_orderkey, floor(l_quantity)::BIGINT f, l_orderkey % 7 AS k FROM lineitem"),
    "op_o24_bits": (lambda c: c.table("orders").select("o_orderkey", F.shiftright("o_orderkey", 3).alias("r"), F.col("o_orderkey").bitwiseAND(5).alias("a"), F.bit_count("o_orderkey").alias("b")), "SELECT o_orderkey, o_orderkey >> 3 AS r, o_orderkey & 5 AS a, bit_count(o_orderkey)::INT b FROM orders"),
    "op_o25_json": (lambda c: c.table("events").select("event_id", F.from_json("props", "k int")["k"].alias("k")), "SELECT event_id, (props->>'k')::INT k FROM events"),
    "op_o26_vectors": (lambda c: c.table("embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 3).alias("norm2")), "SELECT vec_id, len(embedding)::INT n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 3) norm2 FROM embeddings"),
    "op_o29_broadcast": (_broadcast, _JOINED),
    "op_o30_shuffle_hash": (_joined("shuffle_hash"), _JOINED),
    "op_o31_merge": (_joined("merge"), _JOINED),
    "op_o32_left": (lambda c: c.table("customer").join(c.table("events"), F.col("c_custkey") == F.col("user_id"), "left").groupBy("c_custkey").agg(F.count("event_id").alias("n")), "SELECT c_custkey, count(event_id) n FROM customer LEFT JOIN events ON user_id = c_custkey GROUP BY 1"),
    "op_o34_full": (lambda c: c.table("customer").select(F.col("c_custkey").alias("k")).join(c.table("events").select(F.col("user_id").alias("u")).distinct(), F.col("k") == F.col("u"), "full").agg(F.count("k").alias("a"), F.count("u").alias("b"), F.count("*").alias("n")), "SELECT count(c_custkey) a, count(u) b, count(*) n FROM customer FULL JOIN (SELECT DISTINCT user_id u FROM events) ON u = c_custkey"),
    "op_o35_semi": (lambda c: c.table("customer").join(c.table("events"), F.col("c_custkey") == F.col("user_id"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events)"),
    "op_o36_anti": (lambda c: c.table("orders").join(c.table("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)"),
    "op_o37_cross": (lambda c: cross(c.table("region"), c.table("nation"), allow=True).agg(F.count("*").alias("n")), "SELECT count(*) n FROM region, nation"),
    "op_o38_theta": (lambda c: c.table("region").join(F.broadcast(c.table("nation")), F.col("r_regionkey") < F.col("n_regionkey")).select("r_name", "n_name"), "SELECT r_name, n_name FROM region JOIN nation ON r_regionkey < n_regionkey"),
    "op_o39_interval": (
        lambda c: interval_join(_secs(c).select("user_id", "event_id", "sec"), _secs(c).select("user_id", F.col("event_id").alias("other_id"), F.col("sec").alias("other_sec")), ["user_id"], "sec", "other_sec", 3600).select("event_id", "other_id"),
        "SELECT a.event_id, b.event_id AS other_id FROM events a JOIN events b ON a.user_id = b.user_id AND floor(epoch(b.ts)) > floor(epoch(a.ts)) AND floor(epoch(b.ts)) - floor(epoch(a.ts)) <= 3600",
    ),
    "op_o40_asof": (
        lambda c: asof(c.table("events"), "user_id", ["ts", "event_id"], F.col("event_type") == "view", "event_id").filter("event_type = 'purchase'").select("event_id", "found"),
        "SELECT event_id, found FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS found FROM events) WHERE event_type = 'purchase'",
    ),
    "op_o41_topk_per_key": (lambda c: top_per_key(c.table("orders"), "o_custkey", [F.desc("o_totalprice"), "o_orderkey"], 3).select("o_custkey", "o_orderkey"), "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3"),
    "op_o43_path": (
        lambda c: c.table("orders").join(c.table("customer"), F.col("o_custkey") == F.col("c_custkey")).join(c.table("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(c.table("region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n")),
        "SELECT r_name, count(*) n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    ),
    "op_o45_group": (lambda c: c.table("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) q, count(*) n FROM lineitem GROUP BY 1, 2"),
    "op_o45_salted_group": (lambda c: salted_count(c.table("lineitem"), "l_returnflag"), "SELECT l_returnflag, count(*) n FROM lineitem GROUP BY 1"),
    "op_o47_count_distinct": (lambda c: c.table("lineitem").agg(F.count_distinct("l_partkey").alias("p"), F.count_distinct("l_suppkey").alias("s")), "SELECT count(DISTINCT l_partkey) p, count(DISTINCT l_suppkey) s FROM lineitem"),
    "op_o48_approx_distinct": (lambda c: c.table("lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("p")), None),
    "op_o49_conditional": (lambda c: c.table("orders").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_orderpriority") == "1-URGENT").alias("u")), "SELECT count(*) FILTER (o_orderstatus = 'F') f, count(*) FILTER (o_orderpriority = '1-URGENT') u FROM orders"),
    "op_o50_collect": (lambda c: c.table("lineitem").groupBy("l_orderkey").agg(F.array_join(F.sort_array(F.collect_set("l_suppkey")), ",").alias("s")), "SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') s FROM lineitem GROUP BY 1"),
    "op_o51_quantiles": (lambda c: c.table("orders").agg(F.round(F.percentile("o_totalprice", 0.5), 2).alias("median")), "SELECT round(quantile_cont(o_totalprice, 0.5), 2) AS median FROM orders"),
    "op_o52_cube": (lambda c: c.table("lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, count(*) n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "op_o52_rollup": (lambda c: c.table("orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "op_o53_having": (lambda c: c.table("orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n > 12"), "SELECT o_custkey, count(*) n FROM orders GROUP BY 1 HAVING count(*) > 12"),
    "op_o54_pivot": (lambda c: c.table("orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).count().na.fill(0), "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS \"F\", count(*) FILTER (o_orderstatus = 'O') AS \"O\" FROM orders GROUP BY 1"),
    "op_o55_rank": (lambda c: c.table("orders").select("o_orderkey", F.row_number().over(_orders_w()).alias("rn"), F.ntile(4).over(_orders_w()).alias("q")), "SELECT o_orderkey, row_number() OVER w::INT rn, ntile(4) OVER w::INT q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)".replace("row_number() OVER w::INT", "(row_number() OVER w)::INT").replace("ntile(4) OVER w::INT", "(ntile(4) OVER w)::INT")),
    "op_o56_lag_lead": (lambda c: c.table("events").select("event_id", F.lag("event_id").over(_events_w()).alias("before"), F.lead("event_id").over(_events_w()).alias("later")), "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "op_o57_running": (lambda c: c.table("events").select("event_id", F.count("*").over(_events_w().rowsBetween(Window.unboundedPreceding, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) n FROM events"),
    "op_o58_range": (
        lambda c: c.table("orders").withColumn("d", F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01"))).select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("d").rangeBetween(-30, 0)).alias("n")),
        "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff('day', DATE '1970-01-01', o_orderdate::DATE) RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) n FROM orders",
    ),
    "op_o61_page": (lambda c: c.table("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10"),
    "op_o62_topk": (lambda c: c.table("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    "op_o64_union_all": (lambda c: c.table("orders").select(F.col("o_custkey").alias("c")).union(c.table("events").select("user_id")), "SELECT o_custkey c FROM orders UNION ALL SELECT user_id FROM events"),
    "op_o65_union_by_name": (lambda c: c.table("region").select("r_name").unionByName(c.table("nation").select("n_name"), allowMissingColumns=True), "SELECT r_name, NULL::VARCHAR n_name FROM region UNION ALL SELECT NULL, n_name FROM nation"),
    "op_o66_union_set": (lambda c: c.table("orders").select(F.col("o_custkey").alias("c")).union(c.table("events").select("user_id")).distinct(), "SELECT o_custkey c FROM orders UNION SELECT user_id FROM events"),
    "op_o68_intersect": (lambda c: c.table("orders").filter("o_orderpriority = '1-URGENT'").select("o_custkey").intersect(c.table("events").select("user_id")), "SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT' INTERSECT SELECT user_id FROM events"),
    "op_o69_except": (lambda c: c.table("customer").select("c_custkey").subtract(c.table("events").select("user_id")), "SELECT c_custkey FROM customer EXCEPT SELECT user_id FROM events"),
    "op_o70_distinct": (lambda c: c.table("orders").select("o_custkey", "o_orderstatus").distinct(), "SELECT DISTINCT o_custkey, o_orderstatus FROM orders"),
    "op_o71_dedup_by": (lambda c: top_per_key(c.table("conversations"), "conv_id", ["turn"], 1).select("conv_id", "turn", "role"), "SELECT conv_id, turn, role FROM conversations QUALIFY row_number() OVER (PARTITION BY conv_id ORDER BY turn) = 1"),
    "op_o72_sample": (lambda c: c.table("lineitem").filter(F.pmod(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey"), F.lit(100)) < 10).select("l_orderkey"), None),
}
