"""Query algebra: immutable nodes that the compiler turns into DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any


@dataclass(frozen=True)
class Var:
    """A query variable; in expressions, its value."""

    name: str


@dataclass(frozen=True)
class Const:
    value: Any


@dataclass(frozen=True)
class Call:
    """A function or operator of the expression language, by its name in ``functions.scalar``."""

    fn: str
    args: tuple = ()


Term = Var | Const
Expr = Var | Const | Call


def term(x) -> Term:
    """'?x' is a variable, anything else a constant."""
    if isinstance(x, (Var, Const)):
        return x
    return Var(x[1:]) if isinstance(x, str) and x.startswith("?") else Const(x)


def expr(x) -> Expr:
    return x if isinstance(x, Call) else term(x)


def call(fn: str, *args) -> Call:
    return Call(fn, tuple(expr(a) for a in args))


# Property paths.
@dataclass(frozen=True)
class Step:
    """One predicate; ``inverse`` swaps subject and object."""

    name: str
    inverse: bool = False


@dataclass(frozen=True)
class Seq:
    parts: tuple


@dataclass(frozen=True)
class Alt:
    parts: tuple


@dataclass(frozen=True)
class Repeat:
    """``least`` 0 or 1; ``most`` 1 for an optional step, None for any number."""

    part: Any
    least: int
    most: int | None = None


@dataclass(frozen=True)
class Negated:
    """Any predicate of the catalog but these."""

    names: tuple


class Query:
    """Base of all nodes."""

    def children(self) -> tuple:
        return tuple(v for v in vars(self).values() if isinstance(v, Query))


@dataclass(frozen=True)
class Pattern(Query):
    s: Any
    p: Any
    o: Any

    def ends(self) -> tuple[Term, Term]:
        return term(self.s), term(self.o)


@dataclass(frozen=True)
class Bgp(Query):
    patterns: tuple

    def children(self) -> tuple:
        return self.patterns


@dataclass(frozen=True)
class Unit(Query):
    """One solution that binds nothing."""


@dataclass(frozen=True)
class Join(Query):
    left: Query
    right: Query
    hint: str | None = None


@dataclass(frozen=True)
class LeftJoin(Query):
    left: Query
    right: Query
    condition: Any = None


@dataclass(frozen=True)
class Minus(Query):
    left: Query
    right: Query


@dataclass(frozen=True)
class Union(Query):
    left: Query
    right: Query


@dataclass(frozen=True)
class Filter(Query):
    body: Query
    condition: Any


@dataclass(frozen=True)
class Exists(Query):
    """Keeps solutions of ``body`` for which ``test`` has one, or none if ``negated``."""

    body: Query
    test: Query
    negated: bool = False


@dataclass(frozen=True)
class Extend(Query):
    body: Query
    var: str
    value: Any


@dataclass(frozen=True)
class Values(Query):
    """Constant solutions; None is unbound."""

    vars: tuple
    rows: tuple


@dataclass(frozen=True)
class VarRef(Query):
    """The solution sequence that a result variable holds."""

    name: str


@dataclass(frozen=True)
class Project(Query):
    """Only the named variables; (expression, name) pairs rename or compute."""

    body: Query
    items: tuple


@dataclass(frozen=True)
class Distinct(Query):
    body: Query


@dataclass(frozen=True)
class Agg:
    """count, sum, avg, min, max, sample, group_concat; ``arg`` None counts solutions."""

    fn: str
    arg: Any = None
    distinct: bool = False


@dataclass(frozen=True)
class Group(Query):
    """Groups by variables or (expression, name); without keys there is one solution always."""

    body: Query
    keys: tuple
    aggs: tuple  # of (name, Agg)
    having: Any = None


@dataclass(frozen=True)
class Slice(Query):
    """ORDER BY with (expression, descending) pairs, then OFFSET and LIMIT."""

    body: Query
    order: tuple = ()
    limit: int | None = None
    offset: int = 0


@dataclass(frozen=True)
class GraphClause(Query):
    """``body`` over another catalog of the dataset."""

    name: str
    body: Query


@dataclass(frozen=True)
class Ask(Query):
    body: Query


@dataclass(frozen=True)
class Construct(Query):
    """Triples (s, p, o) made from a template of (s, p, o) terms."""

    template: tuple
    body: Query


@dataclass(frozen=True)
class Table(Query):
    """A query outside the graph: SQL text over result variables, or a function of the environment."""

    make: Any
    reads: tuple = field(default=())


def walk(query: Query):
    """The node and all below it."""
    yield query
    for child in query.children():
        yield from walk(child)


def references(query: Query) -> set[str]:
    """Names of the result variables that a query reads."""
    found = {n.name for n in walk(query) if isinstance(n, VarRef)}
    for node in walk(query):
        if isinstance(node, Table):
            found |= set(node.reads)
    return found
