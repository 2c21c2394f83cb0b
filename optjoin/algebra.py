"""Queries as trees: blocks of patterns under joins, optional joins, unions, filters and a projection."""

from __future__ import annotations

import re
from dataclasses import dataclass, field


class QueryError(ValueError):
    """A query that the engine refuses, and why."""


class NotWellDesigned(QueryError):
    pass


class Disconnected(QueryError):
    pass


class TooManyArms(QueryError):
    pass


@dataclass(frozen=True)
class Pattern:
    """Rows of a table under constants, as bindings of variables.

    cols maps a column or SQL expression to a variable ("?x") or a constant. semantics: "set" makes
    bindings distinct, "bag" keeps one per row and so needs an identity among the variables.
    """

    name: str
    table: str
    cols: tuple[tuple[str, object], ...]
    where: str | None = None
    semantics: str = "bag"

    @property
    def vars(self) -> frozenset[str]:
        return frozenset(t[1:] for _, t in self.cols if isinstance(t, str) and t.startswith("?"))


def pattern(name: str, table: str, where: str | None = None, semantics: str = "bag", **cols: object) -> Pattern:
    return Pattern(name, table, tuple(cols.items()), where, semantics)


@dataclass(frozen=True)
class Block:
    patterns: tuple[Pattern, ...]


@dataclass(frozen=True)
class Join:
    left: object
    right: object


@dataclass(frozen=True)
class LeftJoin:
    left: object
    right: object


@dataclass(frozen=True)
class Union:
    left: object
    right: object


@dataclass(frozen=True)
class Filter:
    child: object
    expr: str
    vars: frozenset[str]


@dataclass(frozen=True)
class Query:
    body: object
    select: tuple[str, ...]
    distinct: bool = False
    options: dict = field(default_factory=dict, hash=False, compare=False)


def block(*patterns: Pattern) -> Block:
    return Block(tuple(patterns))


def patterns_of(node) -> list[Pattern]:
    if isinstance(node, Block):
        return list(node.patterns)
    if isinstance(node, Filter):
        return patterns_of(node.child)
    if isinstance(node, Query):
        return patterns_of(node.body)
    return patterns_of(node.left) + patterns_of(node.right)


def variables(node) -> frozenset[str]:
    return frozenset().union(*(p.vars for p in patterns_of(node)))


def certain(node) -> frozenset[str]:
    """Variables that every answer of the node binds."""
    if isinstance(node, Block):
        return variables(node)
    if isinstance(node, Filter):
        return certain(node.child)
    if isinstance(node, LeftJoin):
        return certain(node.left)
    a, b = certain(node.left), certain(node.right)
    return a & b if isinstance(node, Union) else a | b


def has(node, kind) -> bool:
    if isinstance(node, kind):
        return True
    if isinstance(node, Block):
        return False
    if isinstance(node, Filter):
        return has(node.child, kind)
    return has(node.left, kind) or has(node.right, kind)


def serialize(node) -> str:
    """The parenthesised form."""
    if isinstance(node, Block):
        return "[" + " ".join(p.name for p in node.patterns) + "]"
    if isinstance(node, Filter):
        return f"filter({serialize(node.child)}, {node.expr})"
    if isinstance(node, Query):
        return f"{'distinct ' if node.distinct else ''}{','.join(node.select)} <- {serialize(node.body)}"
    sign = {Join: "join", LeftJoin: "opt", Union: "union"}[type(node)]
    return f"({serialize(node.left)} {sign} {serialize(node.right)})"


def merge_blocks(node):
    """Inner joins of plain blocks become one block."""
    if isinstance(node, Block):
        return node
    if isinstance(node, Filter):
        return Filter(merge_blocks(node.child), node.expr, node.vars)
    left, right = merge_blocks(node.left), merge_blocks(node.right)
    if isinstance(node, Join) and isinstance(left, Block) and isinstance(right, Block):
        return Block(left.patterns + right.patterns)
    return type(node)(left, right)


def check_optional(node, outside: frozenset[str] = frozenset()) -> None:
    """A variable of an optional part that stands outside the optional join must stand on its left side."""
    if isinstance(node, Block):
        return
    if isinstance(node, Filter):
        return check_optional(node.child, outside)
    if isinstance(node, LeftJoin):
        loose = (variables(node.right) & outside) - variables(node.left)
        if loose:
            raise NotWellDesigned(f"optional variables used outside: {sorted(loose)}")
    check_optional(node.left, outside | (frozenset() if isinstance(node, Union) else variables(node.right)))
    check_optional(node.right, outside | (frozenset() if isinstance(node, Union) else variables(node.left)))


def check_union(node, outside: frozenset[str] = frozenset()) -> None:
    """A variable of one arm that stands outside the union must stand in both arms."""
    if isinstance(node, Block):
        return
    if isinstance(node, Filter):
        return check_union(node.child, outside)
    a, b = variables(node.left), variables(node.right)
    if isinstance(node, Union):
        if (a ^ b) & outside:
            raise NotWellDesigned(f"variables of one union arm used outside: {sorted((a ^ b) & outside)}")
        a = b = frozenset()
    check_union(node.left, outside | b)
    check_union(node.right, outside | a)


def check_filters(node) -> None:
    """A filter may only name variables of what it filters."""
    if isinstance(node, Block):
        return
    if isinstance(node, Filter):
        if not node.vars <= variables(node.child):
            raise NotWellDesigned(f"unsafe filter: {sorted(node.vars - variables(node.child))}")
        return check_filters(node.child)
    check_filters(node.left)
    check_filters(node.right)


def union_compatible(a, b) -> bool:
    return variables(a) == variables(b)


def conjuncts(expr: str, used: frozenset[str]) -> list[tuple[str, frozenset[str]]]:
    """A conjunction as its parts, each with the variables it names; anything else, and what holds quotes or brackets, stays whole."""
    parts = re.split(r"\s+AND\s+", expr, flags=re.I)
    if len(parts) == 1 or re.search(r"['\"`()]|\bBETWEEN\b|\bCASE\b|\bOR\b", expr, re.I):
        return [(expr, used)]
    return [(x, frozenset(v for v in used if re.search(rf"\b{re.escape(v)}\b", x))) for x in parts]


# Rewrites. Each returns the node unchanged where it doesn't apply.


def rule1(node):
    if isinstance(node, LeftJoin) and isinstance(node.left, Union):
        return Union(LeftJoin(node.left.left, node.right), LeftJoin(node.left.right, node.right))
    return node


def rule2(node):
    if isinstance(node, Join) and isinstance(node.left, Union):
        return Union(Join(node.left.left, node.right), Join(node.left.right, node.right))
    if isinstance(node, Join) and isinstance(node.right, Union):
        return Union(Join(node.left, node.right.left), Join(node.left, node.right.right))
    return node


def rule4(node):
    """A filter on variables that the left side of an optional join surely binds moves there."""
    if isinstance(node, Filter) and isinstance(node.child, LeftJoin) and node.vars <= certain(node.child.left):
        return LeftJoin(rule4(Filter(node.child.left, node.expr, node.vars)), node.child.right)
    return node


def rule5(node):
    if isinstance(node, Filter) and isinstance(node.child, Union):
        return Union(*(Filter(x, node.expr, node.vars) for x in (node.child.left, node.child.right)))
    return node


@dataclass(frozen=True)
class Arm:
    """A union-free tree; families: of each use of rule 3, (its number, the arm, the parent's variables, the optional part)."""

    tree: object
    families: tuple[tuple[int, int, frozenset[str], object], ...] = ()


def normal_form(node, limit: int = 32) -> list[Arm]:
    """Union normal form by rules 1, 2, 3 and 5; refuses more than `limit` arms."""
    number = iter(range(10**6))

    def expand(n) -> list[Arm]:
        if isinstance(n, Block):
            return [Arm(n)]
        if isinstance(n, Union):
            return expand(n.left) + expand(n.right)
        if isinstance(n, Filter):
            return [Arm(Filter(a.tree, n.expr, n.vars), a.families) for a in expand(n.child)]
        left, right = expand(n.left), expand(n.right)
        out = []
        for a in left:
            family = next(number) if isinstance(n, LeftJoin) and len(right) > 1 else None
            for i, b in enumerate(right):
                mark = () if family is None else ((family, i, variables(a.tree), b.tree),)
                out.append(Arm(type(n)(a.tree, b.tree), a.families + b.families + mark))
        if len(out) > limit:
            raise TooManyArms(f"over {limit} union arms")
        return out

    return expand(node)
