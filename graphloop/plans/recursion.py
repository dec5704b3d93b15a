"""Recursive construct queries and their translation to loops."""

from __future__ import annotations

from dataclasses import dataclass

from graphloop.functions.scalar import invents
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import Fixpoint, Let, Loop, Procedure
from graphloop.plans.runtime import StateCycle, empty_relation, run
from graphloop.relation import Relation


class NotMonotone(ValueError):
    """A step that may lose triples when its input grows."""


@dataclass(frozen=True)
class RecursiveQuery:
    """``step`` makes the temporal graph, a sequence over s, p, o, from itself (a reference to ``name``); ``select`` reads it."""

    step: q.Query
    select: q.Query
    name: str = "graph"


def is_well_designed(query: q.Query) -> bool:
    """Whether every variable of an optional part that is used outside it also occurs in its mandatory part."""

    def scope(node: q.Query) -> set[str]:
        found: set[str] = set()
        for n in q.walk(node):
            if isinstance(n, q.Pattern):
                found |= {t.name for t in n.ends() if isinstance(t, q.Var)}
            if isinstance(n, q.Project):
                found |= {i if isinstance(i, str) else i[1] for i in n.items}
            if isinstance(n, q.VarRef):
                found |= {"s", "p", "o"}
        return found

    def check(node: q.Query, outside: set[str]) -> bool:
        if isinstance(node, q.LeftJoin):
            if (scope(node.right) & outside) - scope(node.left):
                return False
            return check(node.left, outside | scope(node.right)) and check(node.right, outside | scope(node.left))
        children = node.children()
        return all(check(c, outside.union(*(scope(o) for o in children if o is not c))) for c in children)

    return check(query, set())


def check_monotone(query: q.Query) -> list[str]:
    """Why a query is not accepted as monotone; empty if it is."""
    issues = []
    for node in q.walk(query):
        if isinstance(node, q.Extend):
            issues.append("BIND is not allowed")
        elif isinstance(node, q.Minus):
            issues.append("MINUS is not allowed")
        elif isinstance(node, q.Exists) and node.negated:
            issues.append("NOT EXISTS is not allowed")
        elif isinstance(node, (q.Group, q.Slice, q.Table)):
            issues.append(f"{type(node).__name__} is not allowed")
        elif isinstance(node, q.Project) and any(not isinstance(i, str) and invents(q.expr(i[0])) and not isinstance(i[0], q.Const) for i in node.items):
            issues.append("computed values are not allowed")
    if not is_well_designed(query):
        issues.append("an OPTIONAL is not well designed")
    return issues


def to_procedure(rec: RecursiveQuery, guard: bool = False) -> Procedure:
    """The loop that computes the recursion's fixpoint and then its selection."""
    loop = Loop((Let(rec.name, q.Distinct(rec.step)),), Fixpoint(rec.name), guard=(rec.name,) if guard else ())
    return Procedure([loop]).let("result", rec.select).ret("result")


def recursive_graph(rec: RecursiveQuery, catalog: Catalog, semantics: str = "least", schema: str = "s long, p string, o long") -> Relation:
    """The selection over the fixpoint from the empty graph.

    'least' accepts monotone steps only; 'partial' takes any, and the graph is empty where the
    steps run in a circle without a fixpoint.
    """
    if semantics == "least":
        issues = check_monotone(rec.step)
        if issues:
            raise NotMonotone("; ".join(sorted(set(issues))))
    elif semantics != "partial":
        raise ValueError(f"unknown semantics {semantics!r}")
    start = {rec.name: empty_relation(catalog, schema)}
    try:
        return run(to_procedure(rec, guard=semantics == "partial"), catalog, strict=False, env=start).relation
    except StateCycle:
        return run(Procedure().let("result", rec.select).ret("result"), catalog, strict=False, env=start).relation
