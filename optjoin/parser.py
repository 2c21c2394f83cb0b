"""Query text to trees, and the wrappers around a query: order, page, test of existence, template.

A pattern is three terms (over the triples view) or `table(column: term, ...)`; a column may be a quoted
SQL expression. Terms: ?variable, <name>, "text", numbers. A group is read from left to right.
BIND(expression AS ?variable) stands at the end of the outermost group; Spark SQL evaluates it on each answer.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce as fold
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .algebra import Block, Filter, Join, LeftJoin, Pattern, Query, QueryError, Union, variables
from .engine import run
from .sources.tables import Catalog

_TOKEN = re.compile(r'\s*(?:(?P<var>\?\w+)|<(?P<iri>[^<>\s]*)>|"(?P<text>(?:[^"\\]|\\.)*)"|(?P<number>-?\d+(?:\.\d+)?)|(?P<word>[A-Za-z_]\w*)|(?P<sign>&&|\|\||!=|<=|>=|[{}().,:=<>!*+/-]))')
_SIGNS = {"&&": "AND", "||": "OR", "!": "NOT"}


@dataclass(frozen=True)
class Parsed:
    """A query and what is applied to its answers. template: triples of a CONSTRUCT; names: the answer's columns, some of them computed."""

    query: Query
    ask: bool = False
    template: tuple[tuple[object, object, object], ...] = ()
    order: tuple[tuple[str, bool], ...] = ()
    limit: int | None = None
    offset: int = 0
    computed: tuple[tuple[str, str], ...] = ()
    names: tuple[str, ...] = ()


def _tokens(text: str) -> list[tuple[str, str]]:
    out, at = [], 0
    while text[at:].strip():
        found = _TOKEN.match(text, at)
        if not found:
            raise QueryError(f"unreadable at {text[at:at + 20]!r}")
        out.append((found.lastgroup, found[found.lastgroup]))
        at = found.end()
    return out


def _plain(text: str) -> str:
    return re.sub(r"\\(.)", lambda m: {"n": "\n", "t": "\t", "r": "\r"}.get(m[1], m[1]), text)


class _Reader:
    def __init__(self, text: str):
        self.tokens, self.at, self.numbers = _tokens(text), 0, count(1)
        self.depth, self.binds = 0, []

    def sees(self, *words: str) -> bool:
        kind, value = self.tokens[self.at] if self.at < len(self.tokens) else ("end", "")
        return kind in ("word", "sign") and value.upper() in words

    def takes(self, *words: str) -> bool:
        if self.sees(*words):
            self.at += 1
            return True
        return False

    def needs(self, word: str) -> None:
        if not self.takes(word):
            raise QueryError(f"{word} expected, {self.next()[1] or 'end'!r} found")

    def next(self) -> tuple[str, str]:
        if self.at >= len(self.tokens):
            return "end", ""
        self.at += 1
        return self.tokens[self.at - 1]

    def kind(self) -> str:
        return self.tokens[self.at][0] if self.at < len(self.tokens) else "end"

    def term(self) -> object:
        kind, value = self.next()
        if kind == "number":
            return float(value) if "." in value else int(value)
        if kind in ("var", "iri", "text"):
            return _plain(value) if kind == "text" else value
        raise QueryError(f"a term expected, {value!r} found")

    def pattern(self) -> Pattern:
        name = f"p{next(self.numbers)}"
        if self.kind() != "word":
            return Pattern(name, "triples", tuple(zip("spo", (self.term(), self.term(), self.term()), strict=True)), None, "set")
        table, cols = self.next()[1], []
        self.needs("(")
        while True:
            kind, column = self.next()
            if kind not in ("word", "text"):
                raise QueryError(f"a column expected, {column!r} found")
            self.needs(":")
            cols.append((_plain(column), self.term()))
            if not self.takes(","):
                break
        self.needs(")")
        return Pattern(name, table, tuple(cols))

    def condition(self) -> tuple[str, frozenset[str]]:
        """A parenthesised expression as SQL, and its variables."""
        self.needs("(")
        depth, out, names = 1, [], set()
        while True:
            kind, value = self.next()
            if kind == "end":
                raise QueryError("an open parenthesis")
            depth += (kind == "sign") * ((value == "(") - (value == ")"))
            if not depth:
                return " ".join(out), frozenset(names)
            if kind == "word" and value.upper() == "BOUND":
                self.needs("(")
                v = self.next()[1][1:]
                self.needs(")")
                names.add(v)
                out.append(f"(`{v}` IS NOT NULL)")
            elif kind == "var":
                names.add(value[1:])
                out.append(f"`{value[1:]}`")
            elif kind in ("text", "iri"):
                quoted = (_plain(value) if kind == "text" else value).replace("\\", "\\\\").replace("'", "\\'")
                out.append(f"'{quoted}'")
            else:
                out.append(_SIGNS.get(value, value))

    def bind(self, tree) -> None:
        if self.depth != 1 or tree is None:
            raise QueryError("BIND stands at the end of the outermost group")
        text, names = self.condition()
        found = re.fullmatch(r"(.+) AS `(\w+)`", text, re.IGNORECASE | re.DOTALL)
        known = variables(tree) | {v for v, _ in self.binds}
        if not found or found[2] in known or f"`{found[2]}`" in found[1] or names - {found[2]} - known:
            raise QueryError(f"BIND needs a new variable and an expression of known ones: {text}")
        self.binds.append((found[2], found[1]))

    def group(self):
        self.needs("{")
        self.depth += 1
        tree, filters = None, []
        join = lambda a, b: b if a is None else Block(a.patterns + b.patterns) if isinstance(a, Block) and isinstance(b, Block) else Join(a, b)
        while not self.takes("}"):
            if self.takes("."):
                continue
            if self.takes("BIND"):
                self.bind(tree)
                continue
            if self.binds and not self.sees("FILTER"):
                raise QueryError("a pattern after BIND")
            if self.takes("OPTIONAL"):
                if tree is None:
                    raise QueryError("an optional part without anything before it")
                tree = LeftJoin(tree, self.group())
            elif self.takes("FILTER"):
                filters.append(self.condition())
            elif self.sees("{"):
                inner = self.group()
                while self.takes("UNION"):
                    inner = Union(inner, self.group())
                tree = join(tree, inner)
            else:
                tree = join(tree, Block((self.pattern(),)))
        self.depth -= 1
        if tree is None:
            raise QueryError("an empty group")
        return fold(lambda t, f: Filter(t, *f), filters, tree)


def parse(text: str) -> Parsed:
    """A query text as a tree. Raises QueryError where it can't be read or names unknown variables."""
    r = _Reader(text)
    template, distinct, names, ask = [], False, None, r.takes("ASK")
    if not ask and r.takes("CONSTRUCT"):
        r.needs("{")
        while not r.takes("}"):
            template.append((r.term(), r.term(), r.term()))
            r.takes(".")
        names = sorted({t[1:] for row in template for t in row if isinstance(t, str) and t.startswith("?")})
    elif not ask:
        r.needs("SELECT")
        distinct = r.takes("DISTINCT", "REDUCED")
        if not r.takes("*"):
            names = []
            while r.kind() == "var":
                names.append(r.next()[1][1:])
    r.takes("WHERE")
    body = r.group()
    made = {v for v, _ in r.binds}
    every = variables(body) | made
    names = sorted(every) if names is None else names
    if not names or set(names) - every:
        raise QueryError(f"unknown answer variables: {sorted(set(names) - every)}")
    order, limit, offset = [], None, 0
    if r.takes("ORDER"):
        r.needs("BY")
        while r.kind() == "var" or r.sees("ASC", "DESC"):
            down, wrapped = r.sees("DESC"), r.takes("ASC", "DESC")
            if wrapped:
                r.needs("(")
            order.append((r.next()[1][1:], down))
            if wrapped:
                r.needs(")")
    while r.sees("LIMIT", "OFFSET"):
        word, number = r.next()[1].upper(), int(r.next()[1])
        limit, offset = (number, offset) if word == "LIMIT" else (limit, number)
    if r.kind() != "end":
        raise QueryError(f"unread: {r.next()[1]!r}")
    used = set(names) - made | {v for v in every - made if any(f"`{v}`" in text for _, text in r.binds)}
    used = used or every - made  # each answer counts, also where only constants are computed
    return Parsed(Query(body, tuple(sorted(used, key=lambda v: (v not in names, v))) if made else tuple(names), distinct), ask, tuple(template), tuple(order), limit, offset, tuple(r.binds), tuple(names))


def parse_query(text: str) -> Query:
    """The query alone. A text with BIND computes on its answers and goes through `evaluate`."""
    parsed = parse(text)
    if parsed.computed:
        raise QueryError("BIND is evaluated by evaluate()")
    return parsed.query


def _made(df: DataFrame, template) -> DataFrame:
    """Triples of a template without duplicates; one with an unbound variable isn't made."""
    cell = lambda t: F.col(t[1:]).cast("string") if isinstance(t, str) and t.startswith("?") else F.lit(str(t))
    rows = F.array(*(F.struct(*(cell(t).alias(n) for n, t in zip("spo", row, strict=True))) for row in template))
    return df.select(F.explode(rows).alias("t")).select("t.s", "t.p", "t.o").dropna().distinct()


def evaluate(catalog: Catalog, text: str, **options) -> DataFrame:
    """The answers of a query text. Options are those of engine.run."""
    parsed = parse(text)
    df = run(catalog, parsed.query, **options)
    if parsed.ask:
        return df.limit(1).agg((F.count("*") > 0).alias("found"))
    if parsed.computed:
        for name, text in parsed.computed:
            df = df.withColumn(name, F.expr(text))
        df = df.select(*parsed.names)
        df = df.distinct() if parsed.query.distinct else df
    if parsed.order:
        df = df.orderBy(*(F.col(v).desc() if down else F.col(v) for v, down in parsed.order))
    if parsed.offset:
        df = df.offset(parsed.offset)
    if parsed.limit is not None:
        df = df.limit(parsed.limit)
    return _made(df, parsed.template) if parsed.template else df
