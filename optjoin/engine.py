"""Evaluation: bind, reduce by semi-joins, join in one chain, repair where the structure can't rule it out.

Everything that depends on the query is decided on the driver (plans.structure); the data are only
touched by declared joins, windows and aggregates, so Catalyst and AQE choose how.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce as fold

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .algebra import Block, Disconnected, Filter, Join, LeftJoin, Pattern, Query, QueryError, TooManyArms, Union, check_filters, check_optional, check_union, conjuncts, has, normal_form, patterns_of, rule4, serialize, variables
from .plans import structure as st
from .sources.tables import Catalog, bind, choose_access

#: What each option may be; the first is the default.
CHOICES = {
    "mode": ("exact", "literal"),
    "decision": ("safe", "v0", "literal"),
    "reduce": ("auto", "full", "off", "greedy", "variable_graph"),
    "semijoin": ("auto", "column", "bits", "broadcast", "bloom"),
    "plan": ("auto", "reorder", "nested"),
    "best_match": ("window", "mask", "sorted", "pairwise"),
    "union_strategy": ("components_first", "normalize_first"),
    "union_scope": ("flags", "family", "global", "set"),
    "filter_semantics": ("sparql", "nullify_owner"),
    "filter_place": ("auto", "load", "chain"),
    "distinct": ("auto", "eliminate", "enumerate"),
    "materialize": ("lazy", "persist", "checkpoint"),
    "load": ("plain", "masks"),
    "on_disconnected": ("reject", "cross"),
}
#: A semi-join whose source keeps more than this share of its table is left out, where the answer doesn't hang on it.
WORTH = 0.5


@dataclass
class Options:
    """All variants; see CHOICES. The defaults are exact; `literal`, `v0` and `sorted` show what the printed steps give.

    plan: `reorder` joins all patterns in one chain after the reduction. `auto` does too, but a child block of several
    patterns that hangs together is joined by itself first, so that it is hit or missed as a whole and needs no repair.
    reduce: `full` issues every semi-join of the reduction; `auto` those that the answer hangs on and those that filter a
    large child at its scan by a small, selective parent (see worthwhile).
    best_match `pairwise` compares all rows with all: for small inputs only.
    """

    mode: str = "exact"
    decision: str = "safe"
    reduce: str = "auto"
    passes: int = 1
    semijoin: str = "auto"
    plan: str = "auto"
    best_match: str = "window"
    force_repair: bool = False
    union_strategy: str = "components_first"
    union_scope: str = "flags"
    filter_semantics: str = "sparql"
    filter_place: str = "auto"
    distinct: str = "auto"
    materialize: str = "lazy"
    load: str = "plain"
    on_disconnected: str = "reject"
    sizes: dict[str, int] | None = None
    stats: st.Stats | None = None

    def __post_init__(self) -> None:
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise QueryError(f"{name} must be one of {allowed}, not {getattr(self, name)!r}")
        if self.passes < 1:
            raise QueryError("passes must be at least 1")


@dataclass
class Trace:
    """What a run decided, for explain() and the measures."""

    decision: list[st.Decision] = field(default_factory=list)
    semijoins: list[tuple[str, str, frozenset[str]]] = field(default_factory=list)
    skipped: list[tuple[str, str, frozenset[str]]] = field(default_factory=list)
    order: list[str] = field(default_factory=list)
    units: list[str] = field(default_factory=list)
    before: dict[str, DataFrame] = field(default_factory=dict)
    after: dict[str, DataFrame] = field(default_factory=dict)
    access: dict[str, str] = field(default_factory=dict)
    held: list[DataFrame] = field(default_factory=list)
    chain: DataFrame | None = None
    nullified: DataFrame | None = None
    strategy: str = ""
    arms: int = 1

    def release(self) -> None:
        """Gives back what `materialize="persist"` holds, once the answer has been read."""
        for df in self.held:
            df.unpersist()
        self.held.clear()


# Sizes -------------------------------------------------------------------------------------------


def ratio_of(p) -> float:
    """The share of a table that a pattern is taken to keep: a tenth for each constant and condition."""
    return 10.0 ** -(sum(not (isinstance(t, str) and t.startswith("?")) for _, t in p.cols) + bool(p.where))


def cardinalities(catalog: Catalog, patterns) -> dict[str, int]:
    """Sizes in bytes for ordering, from the optimizer's statistics of each bound pattern: no job. They never affect results."""
    out = {}
    for p in patterns:
        size = int(str(bind(catalog, p)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        out[p.name] = max(1, int(size * ratio_of(p)))  # without column statistics a constant doesn't show
    return out


def exact_cardinalities(frames: dict[str, DataFrame]) -> dict[str, int]:
    """Counted sizes of all patterns in one job."""
    parts = [df.agg(F.count("*").alias("n")).select(F.lit(k).alias("k"), "n") for k, df in frames.items()]
    return {r.k: r.n for r in fold(DataFrame.unionByName, parts).collect()}


def link_stats(catalog: Catalog, patterns) -> st.Stats:
    """Rows and distinct values of the join variables of each pattern, in one job; kept for the session, as an index keeps its counts.

    They choose an order and never affect results, so they are approximate and may be old.
    """
    known = catalog.spark.__dict__.setdefault("_optjoin_stats", {})
    names = [(catalog.folder if p.table not in catalog.given else id(catalog.relations[p.table]), p.table, p.cols, p.where) for p in patterns]
    count = {v: sum(v in p.vars for p in patterns) for p in patterns for v in p.vars}
    todo = {}
    for key, p in zip(names, patterns, strict=True):
        joined = sorted(v for v in p.vars if count[v] > 1)
        if key not in known or not set(joined) <= set(known[key][1]):
            df = bind(catalog, p)
            todo[key] = df.agg(F.count("*").alias("n"), F.map_from_arrays(F.array(*(F.lit(v) for v in joined)), F.array(*(F.approx_count_distinct(v) for v in joined))).alias("d") if joined else F.lit(None).cast("map<string,bigint>").alias("d"))
    if todo:
        rows = fold(DataFrame.unionByName, [df.withColumn("k", F.lit(i)) for i, df in enumerate(todo.values())]).collect()
        for key, r in zip(todo, sorted(rows, key=lambda r: r.k), strict=True):
            known[key] = (float(r.n), {v: float(x) for v, x in (r.d or {}).items()})
    return {p.name: (known[k][0], {v: known[k][1].get(v, known[k][0]) for v in p.vars}) for k, p in zip(names, patterns, strict=True)}


# Reduction ---------------------------------------------------------------------------------------


def semi_join(left: DataFrame, right: DataFrame, on, strategy: str = "auto", exact: bool = True) -> DataFrame:
    """left with a partner in right on these variables. Only keys of the right side move.

    column: distinct keys; bits: a bitmap of one integer key; broadcast: distinct keys sent to all executors, if Spark's
    estimate of them is below its own threshold; bloom: a bitmap of hashed keys of any types, which may keep a little
    more, so it is used only where the answer doesn't hang on the reduction (`exact` false).
    """
    on = sorted(on)
    keys = right.select(*on)
    if strategy == "bits" and len(on) == 1 and dict(left.dtypes)[on[0]] in ("bigint", "int"):
        from .functions.bits import unfold, fold_bits

        return unfold(left, fold_bits(keys, on[0]), on[0])
    if strategy == "bloom" and not exact:
        from .functions.bits import bloom_filter

        return bloom_filter(left, keys, on)
    if strategy == "broadcast":
        keys, limit = keys.distinct(), int(left.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold())
        if int(str(keys._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) <= limit:
            keys = F.broadcast(keys)
    if strategy == "column":
        keys = keys.distinct()
    return left.join(keys, on, "left_semi")


def load_pruned(catalog: Catalog, nodes: list[st.Node]) -> dict[str, DataFrame]:
    """Patterns bound in ascending size, each under masks of the selective ones before it in its block and the blocks above.

    Masks have a fixed number of bits and may keep a little more, which the joins take away.
    """
    from .functions.bits import bloom_filter

    frames: dict[str, DataFrame] = {}
    masks: dict[tuple[int, str], DataFrame] = {}
    for i, x in enumerate(nodes):
        size = cardinalities(catalog, x.patterns)
        for p in sorted(x.patterns, key=lambda p: (size[p.name], p.name)):
            df, pruned = bind(catalog, p), ratio_of(p) < WORTH
            for j in [i, *st.ancestors(nodes, i)]:
                for v in sorted(p.vars):
                    if (j, v) in masks:
                        df, pruned = bloom_filter(df, masks[j, v], [v]), True
            frames[p.name] = df
            if pruned:
                masks |= {(i, v): df.select(v) for v in p.vars if (i, v) not in masks}
    return frames


def broadcast_limit(catalog: Catalog) -> int:
    """What Spark sends to all executors, at most, by its own setting; its default where that is off."""
    limit = int(catalog.spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold())
    return limit if limit > 0 else 10 << 20


def worthwhile(plan, nodes: list[st.Node], ratios: dict[str, float], fixed: set[str], size: dict[str, int], limit: int):
    """(entry, whether the answer hangs on it, whether `auto` issues it) of a reduction.

    Joins inside a block already drop what has no partner there. A child is worth reducing by its parent where that turns
    into a filter at the scan: the parent is selective and small enough to be sent, and the child isn't. One such filter
    for each pattern, by the parent as it is bound: so no plan is repeated inside another.
    """
    home = {p.name: i for i, x in enumerate(nodes) for p in x.patterns}
    out, done = [], set()
    for target, source, on in plan:
        needed = target in fixed and source in fixed
        use = needed or (home[target] != home[source] and target not in done and ratios[source] < WORTH and size.get(source, 0) <= limit < size.get(target, 0))
        if use and not needed:
            ratios[target] *= ratios[source]
            done.add(target)
        out.append(((target, source, on), needed, use))
    return out


def reduce_patterns(frames: dict[str, DataFrame], plan, strategy: str = "auto", materialize: str = "lazy", held: list | None = None, needed: set | None = None) -> dict[str, DataFrame]:
    """Frames after the semi-joins. Materialised, a pattern is computed once, however often later steps read it."""
    out = dict(frames)
    last = {target: i for i, (target, _, _) in enumerate(plan)}
    for i, (target, source, on) in enumerate(plan):
        exact = needed is None or i in needed
        out[target] = semi_join(out[target], out[source] if exact else frames[source], on, strategy, exact)
        if materialize == "persist":
            later = any(s == target for _, s, _ in plan[i + 1 :]) or last[target] == i
            if later:
                out[target] = out[target].persist()
                if held is not None:
                    held.append(out[target])
        elif materialize == "checkpoint":
            from .lineage import checkpointed

            out[target] = checkpointed(out[target])
    return out


def join_block(frames: dict[str, DataFrame], patterns, stats: st.Stats | None, size: dict[str, int]) -> DataFrame:
    """The inner join of one block that hangs together."""
    nodes = [st.Node("", list(patterns))]
    order = [p for _, p in (st.cost_order(nodes, stats) if stats else st.chain_order(nodes, size))]
    out, have = frames[order[0].name], set(order[0].vars)
    for p in order[1:]:
        out, have = out.join(frames[p.name], sorted(have & p.vars)), have | p.vars
    return out


# Chain, nullification, best match ----------------------------------------------------------------


def _hit(i: int, name: str) -> str:
    return f"_hit_{i}_{name}"


def _ok(i: int) -> str:
    return f"_ok_{i}"


def chain_join(frames: dict[str, DataFrame], nodes: list[st.Node], order, gated: bool = True, cross: bool = False) -> DataFrame:
    """All patterns in one chain: core misses drop the row, child misses leave nulls.

    A later pattern of a child block joins only where the earlier ones of the block, and its parent
    block, were hit; the flag stays in the join condition beside the equalities, so it is a hash join.
    """
    out: DataFrame | None = None
    hits: dict[int, list[str]] = {}
    for i, p in order:
        right = frames[p.name]
        if out is None:
            out = right
            hits.setdefault(i, [])
            continue
        shared = sorted(set(out.columns) & p.vars)
        if not shared and not cross:
            raise Disconnected(f"{p.name} shares no variable with the patterns before it")
        renamed = [F.col(v).alias(f"_r_{v}" if v in shared else v) for v in right.columns]
        condition = [F.col(v) == F.col(f"_r_{v}") for v in shared]
        child = nodes[i].parent is not None
        if child:
            flag = _hit(i, p.name)
            renamed.append(F.lit(True).alias(flag))
            if gated:
                gate = list(hits.get(i, [])) or [h for a in st.ancestors(nodes, i)[:1] for h in hits.get(a, [])]
                condition += [F.col(g) for g in gate[-1:]]
        test = fold(lambda a, b: a & b, condition) if condition else F.lit(True)
        keep = [*out.columns, *(v for v in right.columns if v not in shared)]
        out = out.join(right.select(*renamed), test, "left" if child else "inner")
        out = out.select(*keep, *([F.coalesce(F.col(flag), F.lit(False)).alias(flag)] if child else []))
        if child:
            hits.setdefault(i, []).append(flag)
        else:
            hits.setdefault(i, [])
    return out


def block_flags(df: DataFrame, nodes: list[st.Node], filters: bool = False) -> DataFrame:
    """_ok_i of every child block: all its patterns hit, its parent ok, and (if asked) its filters true."""
    for i, x in enumerate(nodes):
        if x.parent is None:
            continue
        test = fold(lambda a, b: a & b, [F.col(_hit(i, p.name)) for p in x.patterns])
        if nodes[x.parent].parent is not None:
            test = test & F.col(_ok(x.parent))
        if filters:
            for expr, _ in x.filters:
                test = test & F.coalesce(F.expr(expr), F.lit(False))
        df = df.withColumn(_ok(i), test)
    return df.drop(*(c for c in df.columns if c.startswith("_hit_")))


def own_vars(nodes: list[st.Node], i: int) -> list[str]:
    """Variables first bound in a block."""
    above = frozenset().union(*(nodes[a].vars for a in st.ancestors(nodes, i))) if nodes[i].parent is not None else frozenset()
    return sorted(nodes[i].vars - above)


def _id(i: int, name: str) -> str:
    return f"_id_{i}_{name}"


def _ids(columns, i: int) -> list[str]:
    return [c for c in columns if c.startswith(f"_id_{i}_")]


def numbered(frames: dict[str, DataFrame], nodes: list[st.Node]) -> dict[str, DataFrame]:
    """Each row of a pattern with a number of its own, so that repair can tell repeated rows from the copies it makes."""
    out = dict(frames)
    for i, x in enumerate(nodes):
        for p in x.patterns:
            if p.semantics == "bag":
                out[p.name] = out[p.name].withColumn(_id(i, p.name), F.monotonically_increasing_id())
    return out


def nullify(df: DataFrame, nodes: list[st.Node]) -> DataFrame:
    """A block that isn't ok loses what it bound; what its parents bound stays."""
    owner = {v: i for i, x in enumerate(nodes) if x.parent is not None for v in own_vars(nodes, i) + _ids(df.columns, i)}
    keep = [F.when(F.col(_ok(owner[c])), F.col(c)).alias(c) if c in owner else F.col(c) for c in df.columns]
    return df.select(*keep)


def subsumed_by(a: dict[str, Column], b: dict[str, Column]) -> Column:
    """Whether row a agrees with row b where it is bound, and b binds more."""
    agree = fold(lambda x, y: x & y, [a[c].isNull() | (a[c] == b[c]) for c in a])
    nulls = lambda r: fold(lambda x, y: x + y, [r[c].isNull().cast("int") for c in r])
    return F.coalesce(agree, F.lit(False)) & (nulls(b) < nulls(a))


def best_match(df: DataFrame, nodes: list[st.Node], method: str = "window") -> DataFrame:
    """Without subsumed rows and without the equal copies that nullification makes. df holds all variables and the _ok flags.

    Rows are told apart by their numbers (see `numbered`), so repeated rows of the tables stay repeated. window and mask
    go by the flags; pairwise and sorted take a null for a miss, so they are for data without nulls.
    """
    names = [c for c in df.columns if not c.startswith("_ok_")]
    flags = [c for c in df.columns if c.startswith("_ok_")]
    df = df.dropDuplicates(names + flags)
    kids = [i for i in range(1, len(nodes)) if _ok(i) in flags]
    if method == "window":
        for i in sorted(kids, key=lambda k: -len(st.ancestors(nodes, k))):
            inside = st.subtree(nodes, i)
            hidden = {v for j in inside for v in [*own_vars(nodes, j), *_ids(names, j), _ok(j)]}
            w = Window.partitionBy(*(c for c in names + flags if c not in hidden))
            df = df.withColumn("_any", F.max(_ok(i)).over(w)).filter(F.col(_ok(i)) | ~F.col("_any")).drop("_any")
        return df
    if method == "pairwise":
        marked = df.withColumn("_n", F.lit(1))
        a, b = marked.alias("a"), df.select(*(F.col(c).alias(f"_b_{c}") for c in names))
        test = subsumed_by({c: F.col(c) for c in names}, {c: F.col(f"_b_{c}") for c in names})
        return a.join(b, test, "left_anti").drop("_n")
    if method == "sorted":
        core = [v for v in names if v in nodes[0].vars or v in _ids(names, 0)]
        w = Window.partitionBy(*core).orderBy(*(F.col(c).asc_nulls_last() for c in names if c not in core))
        rest = [c for c in names if c not in core]
        before = df.withColumn("_p", F.lag(F.struct(*rest)).over(w)) if rest else df
        if not rest:
            return df
        test = subsumed_by({c: F.col(c) for c in rest}, {c: F.col("_p")[c] for c in rest})
        return before.filter(F.col("_p").isNull() | ~test).drop("_p")
    # mask: rows of one set of missed blocks against those that miss a part of it only
    out = []
    for miss in _masks(nodes, kids):
        state = fold(lambda a, b: a & b, [F.col(_ok(i)) != F.lit(i in miss) for i in kids]) if kids else F.lit(True)
        rows = df.filter(state)
        if miss:
            gone = {v for i in miss for v in [*own_vars(nodes, i), *_ids(names, i)]}
            bound = [c for c in names if c not in gone]
            better = fold(lambda a, b: a | b, [fold(lambda a, b: a & b, [F.col(_ok(i)) != F.lit(i in m) for i in kids]) for m in _masks(nodes, kids) if m < miss])
            others = df.filter(better).select(*(F.col(c).alias(f"_b_{c}") for c in bound)).distinct()
            rows = rows.join(others, fold(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"_b_{c}")) for c in bound]), "left_anti")
        out.append(rows.select(*df.columns))
    return fold(DataFrame.unionByName, out)


def _masks(nodes: list[st.Node], kids: list[int]) -> list[frozenset[int]]:
    """Sets of missed blocks: with a block, all blocks below it."""
    out = [frozenset()]
    for i in kids:
        out += [m | set(st.subtree(nodes, i)) for m in out]
    return sorted(set(map(frozenset, out)), key=lambda m: (len(m), sorted(m)))


# Join-core queries -------------------------------------------------------------------------------


def nested_eval(catalog: Catalog, tree, frames: dict[str, DataFrame] | None = None) -> DataFrame:
    """The query as written: an optional part is joined whole before the left join. The reference plan."""
    if isinstance(tree, Block):
        left = [frames[p.name] if frames else bind(catalog, p) for p in tree.patterns]
        out, rest = left[0], left[1:]
        while rest:
            i = next((i for i, x in enumerate(rest) if set(x.columns) & set(out.columns)), 0)
            x = rest.pop(i)
            on = sorted(set(x.columns) & set(out.columns))
            out = out.join(x, on) if on else out.crossJoin(x)
        return out
    if isinstance(tree, Filter):
        return nested_eval(catalog, tree.child, frames).filter(tree.expr)
    a, b = nested_eval(catalog, tree.left, frames), nested_eval(catalog, tree.right, frames)
    if isinstance(tree, Union):
        return a.unionByName(b, allowMissingColumns=True)
    on = sorted(set(a.columns) & set(b.columns))
    if not on:
        return a.crossJoin(b)
    return a.join(b, on, "left" if isinstance(tree, LeftJoin) else "inner")


def decide(nodes: list[st.Node], options: Options) -> st.Decision:
    rule = {"safe": st.repair_required, "v0": st.repair_required_v0, "literal": st.repair_required_literal}[options.decision]
    found = rule(nodes)
    if not found.repair and any(x.filters for x in nodes[1:]):
        return st.Decision(True, "a filter stands in a child block")
    return st.Decision(True, "forced") if options.force_repair else found


def united(nodes: list[st.Node], chosen: list[int]) -> list[st.Node]:
    """The blocks, with each chosen one as a single pattern of all its variables."""
    out = []
    for i, x in enumerate(nodes):
        if i in chosen:
            one = Pattern(f"unit{i}", "", tuple((v, f"?{v}") for v in sorted(x.vars)), None, "set" if all(p.semantics == "set" for p in x.patterns) else "bag")
            out.append(st.Node(x.name, [one], x.parent, [f for f in x.filters if not f[1] <= x.vars]))
        else:
            out.append(st.Node(x.name, x.patterns, x.parent, list(x.filters)))
    return out


def choose_units(nodes: list[st.Node], options: Options) -> list[int]:
    """The child blocks of several patterns that `auto` joins by themselves: those that hang together without their parent."""
    if options.plan != "auto" or options.force_repair or options.mode != "exact" or options.decision != "safe":
        return []
    edges, out = st.links(nodes), []
    for i, x in enumerate(nodes[1:], 1):
        names = {p.name for p in x.patterns}
        if len(names) > 1 and st.connected(sorted(names), {e: v for e, v in edges.items() if e <= names}):
            out.append(i)
    return out


def place_filters(frames: dict[str, DataFrame], patterns, expr: str, used: frozenset[str], place: str) -> bool:
    """Puts a filter on the scans that hold its variables: a conjunction in parts, anything else on one pattern. False: it waits for the chain."""
    if place == "chain":
        return False
    parts = conjuncts(expr, used)
    homes = [next((p for p in patterns if v <= p.vars), None) for _, v in parts]
    if not all(homes):
        return False
    for (text, v), home in zip(parts, homes, strict=True):
        for p in patterns if len(v) == 1 else [home]:  # a variable's condition holds in every pattern that binds it
            if v <= p.vars:
                frames[p.name] = frames[p.name].filter(text)
    return True


def run_core(catalog: Catalog, tree, options: Options, trace: Trace, frames: dict[str, DataFrame] | None = None) -> DataFrame:
    """All variables, and the _ok flag of every child block, of a query without unions."""
    pulled: list[tuple[str, frozenset[str]]] = []
    while isinstance(tree, Filter):  # a filter over everything: afterwards, or as its owner's miss
        pulled.append((tree.expr, tree.vars))
        tree = tree.child
    nodes = st.block_tree(tree)
    edges = st.links(nodes)
    every = [p for x in nodes for p in x.patterns]
    cross = options.on_disconnected == "cross"
    if not st.connected([p.name for p in every], edges) and not cross:
        raise Disconnected("the patterns fall into parts that share no variable")
    if options.filter_semantics == "nullify_owner":
        rest = []
        for expr, v in pulled:
            own = [i for i in range(1, len(nodes)) if v & set(own_vars(nodes, i))]
            if own and not v - nodes[own[-1]].vars - nodes[0].vars:
                nodes[own[-1]].filters.append((expr, v))
            else:
                rest.append((expr, v))
        pulled = rest
    frames = dict(frames or (load_pruned(catalog, nodes) if options.load == "masks" else {p.name: bind(catalog, p) for p in every}))
    trace.access |= {p.name: choose_access(p) for p in every}
    late: list[str] = []
    for expr, v in nodes[0].filters + [x for x in pulled if x[1] <= nodes[0].vars]:
        if not place_filters(frames, nodes[0].patterns, expr, v, options.filter_place):
            late.append(expr)
    late += [e for e, v in pulled if not v <= nodes[0].vars]
    for x in nodes[1:]:  # a filter of a child that one of its patterns can take is part of that pattern
        x.filters = [f for f in x.filters if len(x.patterns) > 1 or not place_filters(frames, x.patterns, *f, options.filter_place)]
    found = decide(nodes, options)
    units = choose_units(nodes, options)
    if options.reduce not in ("auto", "full") and not found.repair and any(i and i not in units and len(x.patterns) > 1 for i, x in enumerate(nodes)):
        found = st.Decision(True, "the reduction doesn't make the patterns of a child agree")
    ratios = {p.name: ratio_of(p) for p in every}
    alone = units and all(i in units or len(x.patterns) < 2 for i, x in enumerate(nodes[1:], 1))
    choice = any(len(x.patterns) > 2 for x in nodes) if alone else st.has_choice(nodes)
    # Sizes are looked up only where something hangs on them.
    sized = options.reduce not in ("auto", "off") or choice or any(len(x.patterns) > 1 for i, x in enumerate(nodes) if i not in units) or any(ratios[p.name] < WORTH for x in nodes if st.children(nodes, nodes.index(x)) for p in x.patterns)
    size = options.sizes or (cardinalities(catalog, every) if sized else {})
    stats = options.stats or (link_stats(catalog, every) if options.sizes is None and choice else None)
    trace.before |= frames
    if found.repair and len(units) < sum(len(x.patterns) > 1 for x in nodes[1:]) or options.force_repair or any(x.filters for x in nodes[1:]):
        frames = numbered(frames, nodes)
    # Semi-joins: all of them, or those that the answer hangs on and those that filter a scan.
    plan = st.reduction_plan(nodes, size, "auto" if options.reduce == "full" else options.reduce, options.passes)
    hang = {p.name for i, x in enumerate(nodes) if i and i not in units and len(x.patterns) > 1 and not found.repair for p in x.patterns}
    judged = worthwhile(plan, nodes, ratios, hang, size, broadcast_limit(catalog))
    if options.reduce == "auto":
        trace.skipped += [e for e, _, use in judged if not use]
        judged = [x for x in judged if x[2]]
    else:
        judged = [(e, True, True) for e, _, _ in judged]
    plan = [e for e, _, _ in judged]
    trace.semijoins += plan
    frames = reduce_patterns(frames, plan, options.semijoin, options.materialize, trace.held, {i for i, x in enumerate(judged) if x[1]})
    trace.after |= {p.name: frames[p.name] for p in every}
    # Sizes after the reduction: counted where it is materialised, else estimated.
    if options.materialize != "lazy" and options.sizes is None:
        size = exact_cardinalities({p.name: frames[p.name] for p in every})
    elif options.sizes is None and size:
        size = {k: max(1, int(n * ratios[k] / ratio_of(next(p for p in every if p.name == k)))) for k, n in size.items()}
    if stats:
        left = {p.name: ratios[p.name] / ratio_of(p) for p in every}
        stats = {k: (max(1.0, n * left[k]), {v: max(1.0, min(x, n * left[k])) for v, x in d.items()}) for k, (n, d) in stats.items()}
    for i in units:
        unit = join_block(frames, nodes[i].patterns, stats, size)
        for expr, v in nodes[i].filters:
            if v <= nodes[i].vars:
                unit = unit.filter(expr)
        frames[f"unit{i}"] = unit
        size[f"unit{i}"] = min(size.get(p.name, 0) for p in nodes[i].patterns)
        if stats:
            n, d = stats[nodes[i].patterns[0].name]
            for p in nodes[i].patterns[1:]:
                n, d = st.joined_size(n, d, stats[p.name], p.vars & set(d))
            stats[f"unit{i}"] = (n, d)
    nodes = united(nodes, units)
    trace.units += [nodes[i].name for i in units]
    if units:
        apart = [i for i, x in enumerate(nodes) if i and len(x.patterns) > 1]
        if not apart and not any(x.filters for x in nodes[1:]):
            found = st.Decision(False, "every child of several patterns is joined by itself")
        elif not found.repair:
            found = decide(nodes, options)
    trace.decision.append(found)
    order = st.cost_order(nodes, stats) if stats and not cross else st.chain_order(nodes, size)
    trace.order += [p.name for _, p in order]
    out = chain_join(frames, nodes, order, gated=options.mode == "exact", cross=cross)
    trace.chain = out
    out = block_flags(out, nodes, filters=True)
    if found.repair:
        trace.nullified = nullify(out, nodes)
        out = best_match(trace.nullified, nodes, options.best_match)
    out = out.drop(*(c for c in out.columns if c.startswith("_id_")))
    for expr in late:
        out = out.filter(expr)
    return out


# Unions ------------------------------------------------------------------------------------------


def minimum_union(arms: list[DataFrame]) -> DataFrame:
    """Union without subsumed rows and equal copies, over rows of any null pattern (set semantics).

    The null patterns that occur, at most one for each set of columns, are read first; each then costs one anti-join.
    """
    every = fold(lambda a, b: a.unionByName(b, allowMissingColumns=True), arms).distinct()
    names = every.columns
    marked = every.withColumn("_mask", F.concat(*(F.when(F.col(f"`{c}`").isNull(), "1").otherwise("0") for c in names)))
    masks = sorted(r[0] for r in marked.select("_mask").distinct().collect())
    out = []
    for m in masks:
        rows = marked.filter(F.col("_mask") == m)
        bound = [c for c, bit in zip(names, m, strict=True) if bit == "0"]
        lower = [x for x in masks if x != m and all(a <= b for a, b in zip(x, m, strict=True))]
        if lower and bound:
            rows = rows.join(marked.filter(F.col("_mask").isin(lower)).select(*bound).distinct(), bound, "left_anti")
        elif lower:
            rows = rows.filter(F.lit(False))
        out.append(rows.select(*names))
    return fold(DataFrame.unionByName, out)


def compatible_join(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """Inner join in which a null joins anything: rows are split by what they bind, so each part is an equi-join."""
    # Aliases keep the sides apart when both come from one relation.
    out = []
    rest_l, rest_r = [c for c in left.columns if c not in on], [c for c in right.columns if c not in on]
    for a in range(1 << len(on)):
        for b in range(1 << len(on)):
            keys = [c for i, c in enumerate(on) if not (a | b) >> i & 1]
            side = lambda df, m, tag, rest: df.filter(fold(lambda x, y: x & y, [F.col(c).isNull() if m >> i & 1 else F.col(c).isNotNull() for i, c in enumerate(on)])).select(*(F.col(c).alias(tag + c) for c in on), *rest)
            l, r = side(left, a, "_l_", rest_l), side(right, b, "_r_", rest_r)  # noqa: E741
            test = fold(lambda x, y: x & y, [F.col("_l_" + c) == F.col("_r_" + c) for c in keys]) if keys else None
            joined = l.join(r, test) if test is not None else l.crossJoin(r)
            out.append(joined.select(*(F.coalesce("_l_" + c, "_r_" + c).alias(c) for c in on), *rest_l, *rest_r))
    return fold(DataFrame.unionByName, out)


def drop_empty_mappings(df: DataFrame, names: list[str] | None = None) -> DataFrame:
    return df.dropna(how="all", subset=names or df.columns)


def run_union(catalog: Catalog, tree, options: Options, trace: Trace) -> DataFrame:
    try:
        arms = normal_form(tree)
    except TooManyArms:
        trace.strategy = "nested: too many union arms"
        return nested_eval(catalog, tree)
    trace.arms = len(arms)
    shared: dict[str, DataFrame] = {p.name: bind(catalog, p) for p in patterns_of(tree)}
    if options.union_strategy == "components_first" and options.reduce not in ("off", "auto"):
        # Union-free components are reduced once, by themselves; every arm then starts from them.
        for part in components(tree):
            nodes = [st.Node("", list(part.patterns))]
            plan = st.reduction_plan(nodes, options.sizes or cardinalities(catalog, part.patterns), "auto" if options.reduce == "full" else options.reduce)
            trace.semijoins += plan
            shared = reduce_patterns(shared, plan, options.semijoin, options.materialize, trace.held, set())
    done, families = [], {}
    for n, arm in enumerate(arms):
        df = run_core(catalog, arm.tree, options, trace, {p.name: shared[p.name] for p in patterns_of(arm.tree)})
        pulled = arm.tree
        while isinstance(pulled, Filter):
            pulled = pulled.child
        nodes = st.block_tree(pulled)
        for number, i, above, part in arm.families:
            names = {p.name for p in patterns_of(part)}
            at = next(k for k, x in enumerate(nodes) if {p.name for p in x.patterns} & names)
            hit = F.col(_ok(at)) if at else F.lit(True)
            df = df.withColumns({f"_fam_{number}": F.lit(i), f"_famhit_{number}": hit})
            families[number] = above
        done.append(df.drop(*(c for c in df.columns if c.startswith("_ok_"))))
    out = fold(lambda a, b: a.unionByName(b, allowMissingColumns=True), done)
    if options.union_scope in ("global", "set") or (options.union_scope == "family" and families):
        plain = out.drop(*(c for c in out.columns if c.startswith("_fam")))
        if options.union_scope == "global":
            return minimum_union([plain])
        if options.union_scope == "set" and not families:
            return plain.distinct()
        if options.union_scope == "family":
            # Arms that one optional union was split into are made minimal among themselves; other arms stay as they are.
            marks = [c for c in out.columns if c.startswith("_fam_")]
            inside = fold(lambda a, b: a | b, [F.col(c).isNotNull() for c in marks])
            return minimum_union([out.filter(inside).select(*plain.columns)]).unionByName(out.filter(~inside).select(*plain.columns))
    for number, above in sorted(families.items()):
        own, hit = f"_fam_{number}", f"_famhit_{number}"
        others = [c for c in out.columns if c.startswith("_fam_") and c != own]
        w = Window.partitionBy(*sorted(above), *others)
        first = Window.partitionBy(*sorted(above), *others).orderBy(own)
        out = out.withColumns({"_any": F.max(hit).over(w), "_first": F.row_number().over(first)})
        out = out.filter(F.col(own).isNull() | F.col(hit) | (~F.col("_any") & (F.col("_first") == 1))).drop("_any", "_first", own, hit)
    out = out.drop(*(c for c in out.columns if c.startswith("_fam")))
    return out.distinct() if options.union_scope == "set" else out


def components(tree) -> list[Block]:
    """The plain blocks between unions and optional joins."""
    return st.extract_blocks(tree)


# DISTINCT ----------------------------------------------------------------------------------------


def boolean_product(left: DataFrame, right: DataFrame, through: str, outer: bool = False) -> DataFrame:
    """Distinct pairs across a variable that nothing else needs; outer keeps parents without a partner."""
    joined = left.join(right, sorted(set(left.columns) & set(right.columns)), "left" if outer else "inner")
    return joined.drop(through).distinct()


def eliminate(frames: list[DataFrame], wanted: frozenset[str], mode: str = "exact") -> list[DataFrame]:
    """Drops unwanted variables one at a time: all holders are joined, projected and made distinct.

    literal: pairwise products of the first holder with the others through the variable, which loses correlations at hubs.
    """
    frames = list(frames)
    while True:
        every = {v for f in frames for v in f.columns} - wanted
        if not every:
            return frames
        v = min(every, key=lambda x: (sum(x in f.columns for f in frames), x))
        holders = [f for f in frames if v in f.columns]
        rest = [f for f in frames if v not in f.columns]
        if len(holders) == 2 or (mode == "literal" and len(holders) > 2):
            made = [boolean_product(holders[0], f, v) for f in holders[1:]]
        else:
            out = holders[0]
            for f in holders[1:]:
                out = out.join(f, sorted(set(out.columns) & set(f.columns)))
            made = [out.drop(v).distinct()]
        made = [m for m in made if m.columns]
        assert len(rest) + len(made) <= len(frames)
        frames = rest + made


def choose_distinct(query: Query) -> str:
    tree = query.body
    if has(tree, Union) or has(tree, Filter):
        return "enumerate: union or filter"
    nodes = st.block_tree(tree)
    names = [p.name for x in nodes for p in x.patterns]
    if not st.acyclic(names, st.links(nodes)) or st.repair_required(nodes).repair:
        return "enumerate: cyclic"
    wanted = set(query.select)
    if len(nodes) == 1:
        return "eliminate: conjunctive"
    if not wanted & nodes[0].vars:
        return "enumerate: children only"
    return "eliminate: optional" if len(nodes) == 2 else "eliminate: several optional blocks"


def run_distinct(catalog: Catalog, query: Query, options: Options, trace: Trace) -> DataFrame:
    strategy = choose_distinct(query) if options.distinct == "auto" else options.distinct
    if has(query.body, Union) or has(query.body, Filter):
        strategy = "enumerate: union or filter"
    trace.strategy = strategy
    wanted = frozenset(query.select)
    if not strategy.startswith("eliminate"):
        return run_any(catalog, query.body, options, trace).select(*query.select).distinct()
    nodes = st.block_tree(query.body)
    every = [p for x in nodes for p in x.patterns]
    # Patterns that are made distinct are dealt by the variable that most of them lose, so its joins need no other deal.
    lost = sorted(variables(query.body) - wanted)
    hub = max(lost, key=lambda v: (sum(v in p.vars for p in every), v), default=None)
    hub = hub if hub and sum(hub in p.vars for p in every) > 1 else None
    frames = {p.name: bind(catalog, p, hub) for p in every}
    ratios = {p.name: ratio_of(p) for p in every}
    sized = options.reduce not in ("auto", "off") or (len(nodes) > 1 and any(ratios[p.name] < WORTH for x in nodes for p in x.patterns))
    size = options.sizes or (cardinalities(catalog, every) if sized else {})
    plan = st.reduction_plan(nodes, size, "auto" if options.reduce == "full" else options.reduce)
    if options.reduce == "auto":
        plan = [e for e, _, use in worthwhile(plan, nodes, ratios, set(), size, broadcast_limit(catalog)) if use]
    trace.semijoins += plan
    frames = reduce_patterns(frames, plan, options.semijoin, options.materialize, trace.held, set())

    def shrink(i: int, keep: frozenset[str]) -> DataFrame:
        """The distinct bindings of these variables in one block."""
        patterns = nodes[i].patterns
        edges = {e: v for e, v in st.links(nodes).items() if e <= {p.name for p in patterns}}
        cover, steps = st.cover_steps(patterns, keep & nodes[i].vars) if st.acyclic([p.name for p in patterns], edges) else (patterns, [])
        have = frames if options.reduce == "full" else reduce_patterns(frames, steps, options.semijoin)
        kept = eliminate([have[p.name] for p in cover], keep, options.mode)
        out = kept[0]
        for f in kept[1:]:
            on = sorted(set(out.columns) & set(f.columns))
            out = out.join(f, on) if on else out.crossJoin(f)
        return out.distinct()

    def tree(i: int) -> DataFrame:
        """The distinct bindings of what is wanted of a block and all below it, and of what links it to its parent.

        A child that binds nothing wanted adds no row and removes none, so it is left out.
        """
        below = [k for k in st.children(nodes, i) if any(wanted & set(own_vars(nodes, j)) for j in st.subtree(nodes, k))]
        bridges = {k: nodes[i].vars & nodes[k].vars for k in below}
        up = nodes[i].vars & nodes[nodes[i].parent].vars if nodes[i].parent is not None else frozenset()
        out, here = shrink(i, wanted | up | frozenset().union(*bridges.values())), wanted | up
        for n, k in enumerate(below):
            later = frozenset().union(*(bridges[x] for x in below[n + 1 :]))
            out = out.join(tree(k), sorted(bridges[k]), "left")
            drop = [c for c in out.columns if c not in here | later]
            out = out.drop(*drop).distinct() if drop else out
        return out

    return tree(0).select(*query.select).distinct()


# Everything --------------------------------------------------------------------------------------


def run_any(catalog: Catalog, tree, options: Options, trace: Trace) -> DataFrame:
    if has(tree, Union):
        return run_union(catalog, tree, options, trace)
    return run_core(catalog, tree, options, trace)


def run(catalog: Catalog, query: Query, trace: Trace | None = None, **options) -> DataFrame:
    """The answers of a query. Options: see Options; an answer variable may be `ok:<pattern>`, the hit flag of its block."""
    opts = Options(**{**query.options, **options})
    trace = trace if trace is not None else Trace()
    if opts.plan != "nested":
        check_optional(query.body)
    check_union(query.body)
    check_filters(query.body)
    if opts.plan == "nested":
        out = nested_eval(catalog, query.body)
        return out.select(*query.select).distinct() if query.distinct else out.select(*query.select)
    tree = rule4(query.body)
    if query.distinct and not any(v.startswith("ok:") for v in query.select):
        return run_distinct(catalog, Query(tree, query.select, True), opts, trace)
    out = run_any(catalog, tree, opts, trace)
    chosen = []
    nodes = st.block_tree(tree) if not has(tree, Union) and not isinstance(tree, Filter) else []
    for v in query.select:
        if v.startswith("ok:"):
            at = next(i for i, x in enumerate(nodes) if any(p.name == v[3:] for p in x.patterns))
            chosen.append(F.col(_ok(at)).alias("hit"))
        elif v in out.columns:
            chosen.append(F.col(v))
        else:
            raise QueryError(f"unknown variable {v}")
    return out.select(*chosen)


def explain(catalog: Catalog, query: Query, **options) -> str:
    """Structure, decisions, orders and Spark's plan of a query."""
    trace = Trace()
    df = run(catalog, query, trace, **options)
    names, one, two = st.block_graph(query.body)
    lines = [f"query: {serialize(query)}", f"blocks: {names}", f"optional: {one}", f"peers: {two}", *(f"repair: {d.repair} ({d.reason})" for d in trace.decision), f"semi-joins: {[(t, s, sorted(v)) for t, s, v in trace.semijoins]}", f"left out: {[(t, s, sorted(v)) for t, s, v in trace.skipped]}", f"access: {trace.access}", f"joined by themselves: {trace.units}", f"chain: {trace.order}", f"arms: {trace.arms}", f"distinct: {trace.strategy}"]
    return "\n".join(lines) + "\n" + df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


__all__ = ["Catalog", "Options", "Trace", "run", "explain", "variables", "Join"]
