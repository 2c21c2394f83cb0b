"""What the method is compared with; each gives the same answers by another plan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .algebra import Query, patterns_of
from .engine import Trace, nested_eval, run
from .lineage import checkpointed
from .plans import structure as st
from .sources.tables import Catalog, bind


def nested(catalog: Catalog, query: Query) -> DataFrame:
    """As written, without reduction."""
    return run(catalog, query, plan="nested")


def reorder_then_repair(catalog: Catalog, query: Query) -> DataFrame:
    """The chain over raw patterns, always repaired."""
    return run(catalog, query, plan="reorder", reduce="off", force_repair=True)


def reduce_by_variable_graph(catalog: Catalog, query: Query) -> DataFrame:
    """The older reducer: a tree over join variables, rooted at the one with the fewest rows; all patterns of a variable
    reduce each other, upwards through all blocks first and then downwards."""
    return run(catalog, query, plan="reorder", reduce="variable_graph")


def normalize_first(catalog: Catalog, query: Query) -> DataFrame:
    """Unions are normalised before anything is reduced, so arms repeat the reduction."""
    return run(catalog, query, union_strategy="normalize_first")


def enumerate_distinct(catalog: Catalog, query: Query) -> DataFrame:
    """All answers, then duplicates removed."""
    return run(catalog, query, distinct="enumerate")


def full_reducer_inner(catalog: Catalog, query: Query) -> dict[str, DataFrame]:
    """Reduced patterns of one conjunctive block."""
    trace = Trace()
    run(catalog, query, trace, plan="reorder", reduce="full")
    return trace.after


def sql_translation(query: Query) -> str:
    """A query without unions and filters as SQL over its bound patterns; {name} stands for the bindings of a pattern."""

    def text(node, seen: set[str]) -> tuple[str, set[str]]:
        if isinstance(node, st.Block):
            out, have = f"{{{node.patterns[0].name}}}", set(node.patterns[0].vars)
            for p in node.patterns[1:]:
                out, have = f"{out} JOIN {{{p.name}}} USING ({', '.join(sorted(have & p.vars))})", have | p.vars
            return out, have
        a, va = text(node.left, seen)
        b, vb = text(node.right, seen)
        how = "LEFT JOIN" if isinstance(node, st.LeftJoin) else "JOIN"
        return f"(SELECT * FROM {a}) {how} (SELECT * FROM {b}) USING ({', '.join(sorted(va & vb))})", va | vb

    body, _ = text(query.body, set())
    return f"SELECT {'DISTINCT ' if query.distinct else ''}{', '.join(query.select)} FROM {body}"


def translated(catalog: Catalog, query: Query) -> DataFrame:
    """Runs the SQL translation. The views it reads have names of their own, for this statement only."""
    return catalog.spark.sql(sql_translation(query), **{p.name: bind(catalog, p) for p in patterns_of(query.body)})


def under(spark: SparkSession, settings: dict[str, str], make) -> DataFrame:
    """What make() gives, computed under these runtime settings of Spark (adaptive execution, cost-based order, runtime filters)."""
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        return checkpointed(make())
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


__all__ = ["nested", "nested_eval"]
