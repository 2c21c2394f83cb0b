"""Every query the engine registers, with the SQL it is held against where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import baselines, metrics, workloads
from .engine import run
from .operators import catalogue, graph, surface
from .sources.tables import Catalog
from .streaming import replay

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Callable[[Catalog], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = lambda spark, folder: query(Catalog(spark, folder))
    if sql:
        ORACLES[name] = sql


for _name, _query in workloads.QUERIES.items():
    _prefix = _name if _name.split("_")[0] in ("distinct", "union", "filter") else f"core_{_name}"
    _add(_prefix, lambda c, q=_query: run(c, q), workloads.SQL[_name])

_W, _S = workloads.QUERIES, workloads.SQL

for _method in ("mask", "window", "pairwise"):
    for _name in ("two_class", "parent_linked"):
        if _method != "pairwise":
            _add(f"bestmatch_{_method}_{_name}", lambda c, q=_W[_name], m=_method: run(c, q, plan="reorder", best_match=m), _S[_name])
_add("bestmatch_pairwise_cyclic_child", lambda c: run(c, _W["cyclic_child"], plan="reorder", best_match="pairwise"), _S["cyclic_child"])
_add("bestmatch_sorted_two_class", lambda c: run(c, _W["two_class"], plan="reorder", best_match="sorted"), _S["two_class"])
for _name in ("q1", "q1_low", "two_class", "nested6"):
    _add(f"baseline_nested_{_name}", lambda c, q=_W[_name]: baselines.nested(c, q), _S[_name])
    _add(f"baseline_reorder_repair_{_name}", lambda c, q=_W[_name]: baselines.reorder_then_repair(c, q), _S[_name])
for _name in ("q1", "q1_tail", "cyclic_core"):
    _add(f"baseline_variable_graph_{_name}", lambda c, q=_W[_name]: baselines.reduce_by_variable_graph(c, q), _S[_name])
    _add(f"baseline_sql_{_name}", lambda c, q=_W[_name]: baselines.translated(c, q), _S[_name])
for _name in ("q2_union", "union_flags"):
    _add(f"baseline_normalize_first_{_name}", lambda c, q=_W[_name]: baselines.normalize_first(c, q), _S[_name])
for _name in ("distinct_bmm_path", "distinct_hub", "distinct_optional_case1"):
    _add(f"baseline_enumerate_{_name}", lambda c, q=_W[_name]: baselines.enumerate_distinct(c, q), _S[_name])
for _strategy in ("column", "bits", "broadcast", "bloom"):
    _add(f"reduce_{_strategy}_q1_low", lambda c, s=_strategy: run(c, _W["q1_low"], plan="reorder", reduce="full", semijoin=s), _S["q1_low"])
_add("reduce_off_two_class", lambda c: run(c, _W["two_class"], plan="reorder", reduce="off"), _S["two_class"])
_add("reduce_load_masks_nested6", lambda c: run(c, _W["nested6"], load="masks"), _S["nested6"])
for _name in ("q1", "q1_low", "q1_tail", "two_class", "cyclic_core", "cyclic_child", "nested6", "composite_acyclic"):
    _add(f"reorder_full_{_name}", lambda c, q=_W[_name]: run(c, q, plan="reorder", reduce="full"), _S[_name])
for _how in ("persist", "checkpoint"):
    _add(f"materialize_{_how}_two_class", lambda c, h=_how: run(c, _W["two_class"], plan="reorder", reduce="full", materialize=h), _S["two_class"])
for _name in ("two_class", "cyclic_core"):
    _add(f"decision_v0_{_name}", lambda c, q=_W[_name]: run(c, q, plan="reorder", reduce="full", decision="v0"), _S[_name])
_add("baseline_no_aqe_q1_low", lambda c: baselines.under(c.spark, {"spark.sql.adaptive.enabled": "false"}, lambda: baselines.nested(c, _W["q1_low"])), _S["q1_low"])
_add("baseline_cbo_two_class", lambda c: baselines.under(c.spark, {"spark.sql.cbo.enabled": "true", "spark.sql.cbo.joinReorder.enabled": "true"}, lambda: baselines.nested(c, _W["two_class"])), _S["two_class"])
_add("baseline_runtime_filter_q1", lambda c: baselines.under(c.spark, {"spark.sql.optimizer.runtime.bloomFilter.enabled": "true"}, lambda: baselines.nested(c, _W["q1"])), _S["q1"])

_CHILD = "SELECT o_orderkey o FROM orders WHERE o_orderstatus = 'F' AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey = 7)"
_add("reduce_survivors_q1_O", lambda c: metrics.survivors(c, _W["q1"], "O"), f"SELECT o_custkey c, o_orderkey o FROM orders WHERE o_orderkey IN ({_CHILD})")
_add("reduce_survivors_q1_F", lambda c: metrics.survivors(c, _W["q1"], "F"), _CHILD)
_COMPOSITE = _S["composite_acyclic"]
for _pattern, _cols in (("P1", "o, p"), ("P2", "p, s"), ("P3", "o, s"), ("P4", "o, p, s")):
    _add(f"reduce_survivors_composite_{_pattern}", lambda c, p=_pattern: metrics.survivors(c, _W["composite_acyclic"], p), f"SELECT DISTINCT {_cols} FROM ({_COMPOSITE})")
#: The order of the chain is held, so that its rows before repair have a meaning of their own.
_HELD = {"reduce": "off", "sizes": {"C": 1, "O": 2, "L": 3, "S": 4}}
_RAW = "customer LEFT JOIN orders ON o_custkey = c_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey LEFT JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey"
_add("nullify_two_class", lambda c: metrics.nullified(c, _W["two_class"], **_HELD).select("c", "n", "o", "s"), f"SELECT c_custkey c, c_nationkey n, CASE WHEN s_suppkey IS NOT NULL THEN o_orderkey END o, s_suppkey s FROM {_RAW}")
_add(
    "repair_counts_two_class",
    lambda c: metrics.repair_report(c, _W["two_class"], **_HELD),
    f"SELECT *, chain_rows - answers AS removed FROM (SELECT (SELECT count(*) FROM {_RAW}) AS chain_rows, (SELECT count(*) FROM {_RAW} WHERE o_orderkey IS NOT NULL AND s_suppkey IS NULL) AS nullified, (SELECT count(*) FROM ({_S['two_class']})) AS answers)",
)
_add("reduce_greedy_nested6", lambda c: run(c, _W["nested6"], plan="reorder", reduce="greedy"), _S["nested6"])

_SIZES = {"T1": 1, "O": 9, "F": 3, "C": 1, "L": 9, "S": 2}
_add(
    "reduce_report_q1",
    lambda c: metrics.reduction_report(c, _W["q1"], sizes=_SIZES, plan="reorder", reduce="full"),
    """WITH k AS (SELECT c_custkey FROM customer WHERE c_nationkey = 7), f AS (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'),
    r AS (SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM k) AND o_orderkey IN (SELECT o_orderkey FROM f))
    SELECT 'T1' AS pattern, (SELECT count(*) FROM k) AS "before", (SELECT count(*) FROM k) AS "after"
    UNION ALL SELECT 'O', (SELECT count(*) FROM orders), (SELECT count(*) FROM r) UNION ALL SELECT 'F', (SELECT count(*) FROM f), (SELECT count(*) FROM r)""",
)
_add("minimality_q1", lambda c: metrics.minimality(c, _W["q1"], sizes=_SIZES, plan="reorder", reduce="full").filter("pattern <> 'T1'"), "SELECT * FROM (VALUES ('O', 0::BIGINT), ('F', 0::BIGINT)) t(pattern, leftover)")
_add("minimality_composite", lambda c: metrics.minimality(c, _W["composite_acyclic"], plan="reorder", reduce="full"), "SELECT * FROM (VALUES ('P1', 0::BIGINT), ('P2', 0::BIGINT), ('P3', 0::BIGINT), ('P4', 0::BIGINT)) t(pattern, leftover)")
_add("repair_report_two_class", lambda c: metrics.repair_report(c, _W["two_class"]))

for _module in (graph, catalogue, surface, replay):
    for _name, (_query, _sql) in _module.OPERATORS.items():
        _add(_name, _query, _sql)
