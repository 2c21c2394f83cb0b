"""Cost and accuracy measures, as small DataFrames."""

from __future__ import annotations

import uuid
from functools import reduce as fold

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from .algebra import Filter, Query, Union, has, normal_form, patterns_of
from .engine import Trace, run
from .functions.bits import hybrid, run_lengths
from .plans import structure as st
from .sources.tables import Catalog


def _counts(frames: dict[str, DataFrame], name: str) -> DataFrame:
    return fold(DataFrame.unionByName, [df.agg(F.count("*").alias(name)).select(F.lit(k).alias("pattern"), name) for k, df in sorted(frames.items())])


def reduction_report(catalog: Catalog, query: Query, **options) -> DataFrame:
    """(pattern, before, after): rows of each pattern around the reduction."""
    trace = Trace()
    run(catalog, query, trace, **options)
    return _counts(trace.before, "before").join(_counts(trace.after, "after"), "pattern")


def minimality(catalog: Catalog, query: Query, **options) -> DataFrame:
    """(pattern, leftover): reduced rows of each pattern that take part in no answer."""
    trace = Trace()
    run(catalog, query, trace, **options)
    out = {k: df.distinct().join(trace.chain.select(*df.columns).distinct(), df.columns, "left_anti") for k, df in trace.after.items()}
    return _counts(out, "leftover")


def repair_report(catalog: Catalog, query: Query, **options) -> DataFrame:
    """(chain_rows, nullified, removed, answers): rows of the chain, those in which a part of a child was hit only, and what best match takes away."""
    trace = Trace()
    out = run(catalog, query, trace, **{"plan": "reorder", **options})
    blocks: dict[str, list[str]] = {}
    for c in trace.chain.columns:
        if c.startswith("_hit_"):
            blocks.setdefault(c.split("_")[2], []).append(c)
    both = [fold(lambda a, b: a | b, map(F.col, hits)) & ~fold(lambda a, b: a & b, map(F.col, hits)) for hits in blocks.values()]
    part = fold(lambda a, b: a | b, both) if both else F.lit(False)
    rows = trace.chain.agg(F.count("*").alias("chain_rows"), F.count_if(part).alias("nullified")).crossJoin(out.agg(F.count("*").alias("answers")))
    return rows.select("chain_rows", "nullified", (F.col("chain_rows") - F.col("answers")).alias("removed"), "answers")


def survivors(catalog: Catalog, query: Query, pattern: str, **options) -> DataFrame:
    """The distinct bindings of one pattern that are left after the full reduction."""
    trace = Trace()
    run(catalog, query, trace, **{"plan": "reorder", "reduce": "full", **options})
    return trace.after[pattern].distinct()


def nullified(catalog: Catalog, query: Query, **options) -> DataFrame:
    """The rows of the chain after nullification and before best match."""
    trace = Trace()
    run(catalog, query, trace, **{"plan": "reorder", "force_repair": True, **options})
    return trace.nullified.drop(*(c for c in trace.nullified.columns if c.startswith("_")))


def structure_costs(catalog: Catalog, queries: dict[str, Query]) -> DataFrame:
    """(query, patterns, cells, semijoins, arms): cells a row in flight can need, semi-joins of the full reduction, union arms."""
    rows = []
    for name, q in sorted(queries.items()):
        every = patterns_of(q.body)
        plain = not has(q.body, Union) and not has(q.body, Filter)
        plan = st.reduction_plan(st.block_tree(q.body), {p.name: i for i, p in enumerate(every)}) if plain else []
        rows.append((name, len(every), buffer_bound(q), len(plan), arm_count(q)))
    return catalog.spark.createDataFrame(rows, "query string, patterns int, cells int, semijoins int, arms int")


def stage_report(df: DataFrame) -> dict[str, int]:
    """Runs df and sums what its stages read, shuffled and spilled, in bytes."""
    context = df.sparkSession.sparkContext
    group = f"report-{uuid.uuid4().hex}"
    context.setJobGroup(group, group)
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    out = dict.fromkeys(("input", "shuffle_read", "shuffle_write", "spill"), 0)
    for job in tracker.getJobIdsForGroup(group):
        for stage in tracker.getJobInfo(job).stageIds:
            if tracker.getStageInfo(stage):
                s = store.lastStageAttempt(stage)
                for key, value in (("input", s.inputBytes()), ("shuffle_read", s.shuffleReadBytes()), ("shuffle_write", s.shuffleWriteBytes()), ("spill", s.diskBytesSpilled())):
                    out[key] += value
    return out


def scan_count(df: DataFrame) -> int:
    """File scans in the plan of df, before adaptive execution reuses any."""
    return df._jdf.queryExecution().sparkPlan().toString().count("FileScan ")


def observe(df: DataFrame, **measures: Column) -> tuple[DataFrame, Observation]:
    """df with its rows, and these aggregates, counted in flight by the first action that reads it."""
    seen = Observation()
    return df.observe(seen, F.count(F.lit(1)).alias("rows"), *(c.alias(k) for k, c in measures.items())), seen


def semijoin_count(catalog: Catalog, query: Query, **options) -> int:
    trace = Trace()
    run(catalog, query, trace, **options)
    return len(trace.semijoins)


def arm_count(query: Query) -> int:
    return len(normal_form(query.body))


def buffer_bound(query: Query) -> int:
    """Cells a row in flight can need: the sum of the patterns' variables."""
    return sum(len(p.vars) for p in patterns_of(query.body))


def slice_count(triples: DataFrame) -> DataFrame:
    """Two slices for each predicate, one for each subject and each object."""
    return triples.agg((2 * F.count_distinct("p") + F.count_distinct("s") + F.count_distinct("o")).alias("slices"))


def predicate_stats(triples: DataFrame) -> DataFrame:
    return triples.groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("s").alias("n_s"), F.count_distinct("o").alias("n_o"))


def index_size(rows: list[str]) -> tuple[int, int]:
    """Integers stored by run lengths alone and by the hybrid code."""
    return sum(len(run_lengths(r)) for r in rows), sum(len(hybrid(r)[1]) + 1 for r in rows)


def row_code_sizes(triples: DataFrame, predicate: str, row: str = "o", column: str = "s") -> DataFrame:
    """(runs, hybrid): integers that either code needs for the bit rows of one predicate, from positions alone.

    A row of k ones in g groups has g - 1 groups of zeros between them, one more where its first place is 0 and one more
    where its last is; its run code is a first bit and the runs. The hybrid code takes the k positions where they are
    fewer than the runs. Places are dense ids of the column terms, given without a window over all of them.
    """
    from pyspark.sql import Window

    from .operators.graph import dense_ids

    rows = triples.filter(F.col("p") == predicate).select(F.col(row).alias("r"), F.col(column).alias("c"))
    ids = dense_ids(rows, "c")
    placed = rows.join(ids, "c").select("r", "id").distinct()
    w = Window.partitionBy("r").orderBy("id")
    marked = placed.withColumn("new", (F.col("id") - F.coalesce(F.lag("id").over(w), F.lit(-1)) != 1).cast("int"))
    sizes = marked.groupBy("r").agg(F.count("*").alias("k"), F.sum("new").alias("g"), F.min("id").alias("a"), F.max("id").alias("z"))
    sizes = sizes.crossJoin(F.broadcast(ids.agg(F.max("id").alias("n"))))
    runs = 2 * F.col("g") + (F.col("a") > 1).cast("int") + (F.col("z") < F.col("n")).cast("int")
    both = sizes.select(runs.alias("runs"), F.when(F.col("k") < runs - 1, F.col("k")).otherwise(runs).alias("hybrid"))
    return both.agg(F.sum("runs").cast("long").alias("runs"), F.sum("hybrid").cast("long").alias("hybrid"))
