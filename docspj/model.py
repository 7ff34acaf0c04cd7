"""Queries as data: attributes, tables, predicate trees, join graphs."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

OPERATORS = {"=", "<", "<=", ">", ">=", "between", "in"}


@dataclass(frozen=True)
class Attribute:
    """A column to be read out of text: name, what it means, type, and the rule extractor's pattern (its first group is the value)."""

    name: str
    description: str = ""
    dtype: str = "string"
    pattern: str = ""


@dataclass(frozen=True)
class TableSpec:
    """A virtual table: a name and the attributes its documents may hold."""

    name: str
    attributes: tuple[Attribute, ...]

    def __getitem__(self, name: str) -> Attribute:
        for a in self.attributes:
            if a.name == name:
                return a
        raise KeyError(f"table {self.name} has no attribute {name}")


@dataclass(frozen=True)
class Leaf:
    attr: str
    op: str
    args: tuple
    id: int = 0

    def __post_init__(self) -> None:
        if self.op not in OPERATORS:
            raise ValueError(f"unknown operator {self.op}")


@dataclass(frozen=True)
class Node:
    """A conjunction (`op` = and) or disjunction (or) of two children or more."""

    op: str
    children: tuple[Leaf | Node, ...]


Expr = Leaf | Node


def attr(name: str, dtype: str = "string", description: str = "", pattern: str = "") -> Attribute:
    return Attribute(name, description, dtype, pattern)


def eq(a: str, v: object) -> Leaf:
    return Leaf(a, "=", (v,))


def lt(a: str, v: object) -> Leaf:
    return Leaf(a, "<", (v,))


def le(a: str, v: object) -> Leaf:
    return Leaf(a, "<=", (v,))


def gt(a: str, v: object) -> Leaf:
    return Leaf(a, ">", (v,))


def ge(a: str, v: object) -> Leaf:
    return Leaf(a, ">=", (v,))


def between(a: str, low: object, high: object) -> Leaf:
    """A closed range is one filter and one extraction."""
    return Leaf(a, "between", (low, high))


def isin(a: str, values: Sequence) -> Leaf:
    return Leaf(a, "in", tuple(values))


def all_of(*parts: Expr) -> Expr:
    return _joined("and", parts)


def any_of(*parts: Expr) -> Expr:
    return _joined("or", parts)


def _joined(op: str, parts: Sequence[Expr]) -> Expr:
    flat: list[Expr] = []
    for p in parts:
        flat += p.children if isinstance(p, Node) and p.op == op else [p]
    return flat[0] if len(flat) == 1 else Node(op, tuple(flat))


def normalise(expr: Expr) -> Expr:
    """Children of the same operator merged, leaves numbered 1, 2, ... as written."""
    counter = iter(range(1, 1_000_000))

    def walk(e: Expr) -> Expr:
        if isinstance(e, Leaf):
            return replace(e, id=next(counter))
        return _joined(e.op, [walk(c) for c in e.children])

    return walk(expr)


def leaves(expr: Expr | None) -> list[Leaf]:
    if expr is None:
        return []
    return [expr] if isinstance(expr, Leaf) else [x for c in expr.children for x in leaves(c)]


def attributes_of(expr: Expr | None) -> list[str]:
    return list(dict.fromkeys(x.attr for x in leaves(expr)))


def depth(expr: Expr) -> int:
    return 0 if isinstance(expr, Leaf) else 1 + max(depth(c) for c in expr.children)


def fuse_same_attribute(expr: Expr) -> list[list[int]]:
    """Leaf ids by attribute: after the first of a group the others are free, as the value is known."""
    groups: dict[str, list[int]] = {}
    for x in leaves(expr):
        groups.setdefault(x.attr, []).append(x.id)
    return list(groups.values())


def test(leaf: Leaf, value: Column) -> Column:
    """The leaf's predicate; a missing value does not satisfy it."""
    a = [F.lit(x) for x in leaf.args]
    found = {
        "=": lambda: value == a[0],
        "<": lambda: value < a[0],
        "<=": lambda: value <= a[0],
        ">": lambda: value > a[0],
        ">=": lambda: value >= a[0],
        "between": lambda: value.between(a[0], a[1]),
        "in": lambda: value.isin(list(leaf.args)) if leaf.args else F.lit(False),
    }[leaf.op]()
    return F.coalesce(found, F.lit(False))


def test_python(leaf: Leaf, value: object) -> bool:
    if value is None:
        return False
    a = leaf.args
    return {
        "=": lambda: value == a[0],
        "<": lambda: value < a[0],
        "<=": lambda: value <= a[0],
        ">": lambda: value > a[0],
        ">=": lambda: value >= a[0],
        "between": lambda: a[0] <= value <= a[1],
        "in": lambda: value in a,
    }[leaf.op]()


def predicate(expr: Expr | None, column: dict[str, Column]) -> Column:
    """The whole tree as one Column over known values."""
    if expr is None:
        return F.lit(True)
    if isinstance(expr, Leaf):
        return test(expr, column[expr.attr])
    parts = [predicate(c, column) for c in expr.children]
    return reduce((lambda a, b: a & b) if expr.op == "and" else (lambda a, b: a | b), parts)


@dataclass(frozen=True)
class Edge:
    left: str
    left_attr: str
    right: str
    right_attr: str

    def other(self, table: str) -> tuple[str, str, str]:
        """(own attribute, other table, its attribute) seen from a table of the edge."""
        if table == self.left:
            return self.left_attr, self.right, self.right_attr
        return self.right_attr, self.left, self.left_attr


@dataclass(frozen=True)
class JoinGraph:
    tables: tuple[str, ...]
    edges: tuple[Edge, ...]

    @staticmethod
    def of(tables: Sequence[str], edges: Sequence[Edge]) -> JoinGraph:
        """The graph, if its equi-join edges connect all tables."""
        reached, todo = {tables[0]}, True
        while todo:
            new = {t for e in edges for t in (e.left, e.right) if {e.left, e.right} & reached} - reached
            reached |= new
            todo = bool(new)
        if reached != set(tables):
            raise ValueError(f"tables not joined: {sorted(set(tables) - reached)}")
        return JoinGraph(tuple(tables), tuple(edges))

    def between(self, joined: set[str]) -> Iterator[tuple[str, list[Edge]]]:
        """Tables next to a joined set, with the edges that lead there."""
        for t in self.tables:
            found = [e for e in self.edges if t in (e.left, e.right) and ({e.left, e.right} - {t}) & joined]
            if t not in joined and found:
                yield t, found


@dataclass(frozen=True)
class Query:
    """select: (table, attribute) pairs. where: one tree a table. A table alone has no edges."""

    name: str
    tables: tuple[str, ...]
    select: tuple[tuple[str, str], ...]
    where: dict[str, Expr] = field(default_factory=dict)
    edges: tuple[Edge, ...] = ()

    def selected(self, table: str) -> list[str]:
        return list(dict.fromkeys(a for t, a in self.select if t == table))

    def keys(self, table: str) -> list[str]:
        return list(dict.fromkeys(e.other(table)[0] for e in self.edges if table in (e.left, e.right)))

    def tree(self, table: str) -> Expr | None:
        return normalise(self.where[table]) if table in self.where else None

    @property
    def graph(self) -> JoinGraph:
        return JoinGraph.of(self.tables, self.edges)


class Builder:
    """table("customer").where(...).select(...).join("nation", on=("nation_name", "name"))."""

    def __init__(self, name: str):
        self._tables, self._select, self._where, self._edges = [name], [], {}, []

    def where(self, expr: Expr, table: str | None = None) -> Builder:
        table = table or self._tables[-1]
        self._where[table] = all_of(self._where[table], expr) if table in self._where else expr
        return self

    def select(self, *names: str) -> Builder:
        for n in names:
            t, _, a = n.rpartition(".")
            self._select.append((t or self._tables[0], a))
        return self

    def join(self, other: str, on: tuple[str, str], table: str | None = None) -> Builder:
        self._edges.append(Edge(table or self._tables[-1], on[0], other, on[1]))
        self._tables.append(other)
        return self

    def build(self, name: str = "query") -> Query:
        return Query(name, tuple(self._tables), tuple(self._select), dict(self._where), tuple(self._edges))


def table(name: str) -> Builder:
    return Builder(name)
