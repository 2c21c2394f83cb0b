"""Patterns over tables, the triples view, and readers and writers around them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..algebra import Pattern


class Catalog:
    """Tables by name: parquet files of a folder, or registered relations (literal ones, the triples view)."""

    def __init__(self, spark: SparkSession, folder: str | None = None, relations: dict[str, DataFrame] | None = None):
        self.spark, self.folder, self.relations = spark, folder, dict(relations or {})
        self.given = frozenset(self.relations)

    def table(self, name: str) -> DataFrame:
        if name not in self.relations:
            self.relations[name] = self.spark.read.parquet(f"{self.folder}/{name}.parquet")
        return self.relations[name]

    def table_for(self, p: Pattern) -> DataFrame:
        return self.table(p.table)


def _literal(value: object) -> Column:
    return F.lit(value)


def bind(catalog: Catalog, p: Pattern, hub: str | None = None) -> DataFrame:
    """Bindings of one pattern: constants and repeated variables are filters, so they reach the scan.

    Relations keep rows with nulls: a null matches nothing in a join, and a row of the core stays as a miss.
    hub: a variable that the pattern is next joined by; a pattern made distinct is then dealt by it once for both.
    """
    df = catalog.table_for(p)
    if p.where:
        df = df.filter(p.where)
    first: dict[str, str] = {}
    for column, term in p.cols:
        if isinstance(term, str) and term.startswith("?"):
            if term[1:] in first:
                df = df.filter(F.expr(column) == F.expr(first[term[1:]]))
            else:
                first[term[1:]] = column
        else:
            df = df.filter(F.expr(column) == _literal(term))
    out = df.select(*(F.expr(c).alias(v) for v, c in first.items()))
    if p.semantics != "set":
        return out
    return out.repartition(hub).distinct() if hub in out.columns else out.distinct()


#: Table: (subject prefix, key expression, edges {column: prefix}, attributes).
GRAPH = {
    "region": ("region", "r_regionkey", {}, ["r_name"]),
    "nation": ("nation", "n_nationkey", {"n_regionkey": "region"}, ["n_name"]),
    "customer": ("customer", "c_custkey", {"c_nationkey": "nation"}, ["c_name", "c_acctbal", "c_mktsegment"]),
    "supplier": ("supplier", "s_suppkey", {"s_nationkey": "nation"}, ["s_name", "s_acctbal"]),
    "part": ("part", "p_partkey", {}, ["p_name", "p_brand", "p_type", "p_size", "p_retailprice"]),
    "orders": ("order", "o_orderkey", {"o_custkey": "customer"}, ["o_orderstatus", "o_totalprice", "o_orderpriority"]),
    "events": ("event", "event_id", {"user_id": "customer"}, ["event_type", "value"]),
    "labels": ("doc", "doc_id", {}, ["quality", "toxic"]),
}
LINE_ID = "concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity)"


def triples(catalog: Catalog, tables: list[str] | None = None) -> DataFrame:
    """(g, s, p, o, o_num) of the given tables, without duplicates; one scan per table, one row per cell."""
    parts = []
    for name in tables or [*GRAPH, "lineitem"]:
        df = catalog.table(name)
        if name == "lineitem":
            keys = {"l_orderkey": "order", "l_partkey": "part", "l_suppkey": "supplier"}
            subject, edges, literals = F.concat(F.lit("line/"), F.expr(LINE_ID)), keys, ["l_returnflag"]
        else:
            prefix, key, edges, literals = GRAPH[name]
            subject = F.concat(F.lit(prefix + "/"), F.col(key))
        cells = [F.struct(F.lit(c).alias("p"), F.concat(F.lit(to + "/"), F.col(c)).alias("o"), F.lit(None).cast("double").alias("o_num")) for c, to in edges.items()]
        cells += [F.struct(F.lit(c).alias("p"), F.col(c).cast("string").alias("o"), F.expr(f"try_cast(`{c}` AS double)").alias("o_num")) for c in literals]
        parts.append(df.select(F.lit(name).alias("g"), subject.alias("s"), F.explode(F.array(*cells)).alias("c")).select("g", "s", "c.p", "c.o", "c.o_num"))
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out.filter("o is not null").dropDuplicates(["s", "p", "o"])  # a null cell says nothing


def write_triples(df: DataFrame, path: str) -> None:
    """Partitioned by predicate and sorted inside, so that fixed subjects and objects skip row groups."""
    df.repartition("p").sortWithinPartitions("s", "o").write.mode("overwrite").partitionBy("p").parquet(path)


#: The copies of the triples, by the columns that cluster them: of each predicate by subject and by object, and of each subject and object by predicate.
SLICES = {"so": ("p", ("s", "o")), "os": ("p", ("o", "s")), "po": ("s", ("p", "o")), "ps": ("o", ("p", "s"))}


def write_slices(df: DataFrame, path: str, files: int = 64) -> None:
    """All four copies, each sorted inside its files by its key and then by its columns, so that fixed terms skip row groups."""
    for name, (key, rest) in SLICES.items():
        df.repartitionByRange(files, key, *rest).sortWithinPartitions(key, *rest).write.mode("overwrite").parquet(f"{path}/{name}")


def choose_access(p: Pattern, joined: str | None = None) -> str:
    """The copy that serves a triple pattern, by which of its positions are fixed; other tables are scanned.

    joined: the position that joins first, where only the predicate is fixed.
    """
    terms = dict(p.cols)
    if set(terms) != {"s", "p", "o"}:
        return "scan"
    fixed = "".join(k if not (isinstance(v, str) and v.startswith("?")) else "?" for k, v in terms.items())
    if fixed == "?p?":
        return "os" if joined == "o" else "so"
    return {"sp?": "so", "?po": "os", "spo": "so", "s??": "po", "??o": "ps", "s?o": "po", "???": "scan"}[fixed]


class SliceCatalog(Catalog):
    """The triples view over the four copies: each pattern is read from the one that its fixed terms choose."""

    def __init__(self, spark: SparkSession, path: str):
        super().__init__(spark, path)
        self.path = path

    def table_for(self, p: Pattern) -> DataFrame:
        name = choose_access(p)
        return self.spark.read.parquet(f"{self.path}/{'so' if name == 'scan' else name}")
