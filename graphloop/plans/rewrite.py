"""Rewrites of procedures before they run: deltas, invariants, dead values."""

from __future__ import annotations

from dataclasses import fields, is_dataclass, replace
from functools import reduce

from graphloop.plans import query as q
from graphloop.plans.layout import assigned, leaves, scope
from graphloop.plans.procedure import AskTrue, Fixpoint, Let, Loop, Procedure, references


def rename(node, old: str, new: str):
    """A query that reads ``new`` instead of ``old``."""
    if isinstance(node, q.VarRef):
        return q.VarRef(new) if node.name == old else node
    if isinstance(node, q.Query) and is_dataclass(node):
        changed = {f.name: rename(getattr(node, f.name), old, new) for f in fields(node)}
        return replace(node, **changed)
    if isinstance(node, tuple):
        return tuple(rename(x, old, new) for x in node)
    return node


def count_reads(node: q.Query, name: str) -> int:
    return sum(1 for n in q.walk(node) if isinstance(n, q.VarRef) and n.name == name)


def is_inflationary(body: tuple, var: str) -> bool:
    """Whether the last assignment only adds to ``var``: var = distinct(... union var)."""
    if not body or not isinstance(body[-1], Let) or body[-1].var != var:
        return False
    query = body[-1].query
    return isinstance(query, q.Distinct) and isinstance(query.body, q.Union) and q.VarRef(var) in (query.body.left, query.body.right)


def delta_rewrite(loop: Loop) -> list | None:
    """Statements that extend only what the last round found, or None if the loop is not of the form.

    Needs a fixpoint over a variable that only grows, whose body reads it once before the
    growing assignment; other reads would need all its values.
    """
    if not isinstance(loop.until, Fixpoint) or not is_inflationary(loop.body, loop.until.var):
        return None
    var, new = loop.until.var, f"_new_{loop.until.var}"
    *steps, grow = loop.body
    if any(not isinstance(s, Let) or s.split for s in steps) or sum(count_reads(s.query, var) for s in steps) != 1:
        return None
    side = grow.query.body.left if grow.query.body.right == q.VarRef(var) else grow.query.body.right
    if var in references(side):
        return None
    body = [replace(s, query=rename(s.query, var, new), lazy=True) for s in steps]
    fresh = q.Exists(q.Distinct(side), q.VarRef(var), negated=True)
    body += [Let(new, fresh), Let(var, q.Union(q.VarRef(var), q.VarRef(new)))]
    done = AskTrue(q.Filter(q.Group(q.VarRef(new), (), (("n", q.Agg("count")),)), q.call("=", "?n", 0)))
    start = [Let(var, q.Distinct(q.VarRef(var))), Let(new, q.VarRef(var), lazy=True)]
    return [*start, Loop(tuple(body), done, loop.max_rounds)]


def hoist_invariants(loop: Loop) -> list:
    """Moves assignments whose inputs the loop never changes in front of it."""
    changed = assigned(loop.body)
    moved, kept = [], []
    for s in loop.body:
        if isinstance(s, Let) and not references(s.query) & (changed - {m.var for m in moved}) and sum(1 for x in loop.body if isinstance(x, Let) and x.var == s.var) == 1:
            moved.append(s)
        else:
            kept.append(s)
    return [*moved, replace(loop, body=tuple(kept))] if moved and kept else [loop]


def hoist_parts(loop: Loop, known: dict[str, frozenset], number: int = 0) -> list:
    """Moves parts of a loop's queries that no round changes in front of it, where they are computed once.

    Operands of a join are regrouped for that: those that the loop never changes and that share
    variables become one part. Joins are commutative and associative, with unbound variables too.
    """
    changed = assigned(loop.body)
    moved: dict[q.Query, str] = {}

    def fixed(node: q.Query) -> bool:
        return not any(isinstance(n, q.Table) for n in q.walk(node)) and not references(node) & changed

    def name(node: q.Query) -> q.Query:
        if isinstance(node, (q.VarRef, q.Values, q.Unit)):
            return node
        found = next((v for k, v in moved.items() if k == node), None)
        if found is None:
            found = moved[node] = f"_part{number}_{len(moved)}"
        return q.VarRef(found)

    def take(node: q.Query, known) -> q.Query:
        if fixed(node):
            return name(node)
        if isinstance(node, q.Join) and node.hint is None:
            groups: list[tuple[q.Query, frozenset]] = []
            rest = []
            for leaf in leaves(node):
                if not fixed(leaf):
                    rest.append(take(leaf, known))
                    continue
                mine = (leaf, scope(leaf, known))
                near = [g for g in groups if g[1] & mine[1]]
                for g in near:
                    groups.remove(g)
                    mine = (q.Join(g[0], mine[0]), g[1] | mine[1])
                groups.append(mine)
            return reduce(q.Join, [*(name(g) for g, _ in groups), *rest])
        if isinstance(node, q.Query) and is_dataclass(node) and not isinstance(node, (q.Bgp, q.GraphClause)):
            return replace(node, **{f.name: take(getattr(node, f.name), known) for f in fields(node) if isinstance(getattr(node, f.name), q.Query)})
        return node

    body = []
    for s in loop.body:
        if isinstance(s, Let) and s.split is None:
            s2 = replace(s, query=take(s.query, known))
            known = {**known, s.var: scope(s.query, known)}
            body.append(s2)
        else:
            body.append(s)
    return [*(Let(v, k, lazy=True) for k, v in moved.items()), replace(loop, body=tuple(body))]


def optimise(proc: Procedure) -> Procedure:
    """Hoists invariants and turns growing fixpoints into deltas."""
    out: list = []
    known: dict[str, frozenset] = {}
    for s in proc.statements:
        if isinstance(s, Loop):
            for part in hoist_invariants(s):
                for x in hoist_parts(part, known, len(out)) if isinstance(part, Loop) else [part]:
                    out += (delta_rewrite(x) if isinstance(x, Loop) else None) or [x]
        else:
            out.append(s)
            if isinstance(s, Let):
                known = {**known, s.var: scope(s.query, known)}
    return Procedure(out)


def dead_after(proc: Procedure) -> dict[str, int]:
    """For each variable the last top-level statement that reads it; its value may go after that."""
    last: dict[str, int] = {}

    def reads(s) -> set[str]:
        if isinstance(s, Let):
            return references(s.query)
        if isinstance(s, Loop):
            inside = set().union(*(reads(x) for x in s.body), assigned(s.body))
            c = s.until
            return inside | ({c.var} if hasattr(c, "var") else references(c.query) if isinstance(c, AskTrue) else set())
        return {s.var}

    for k, s in enumerate(proc.statements):
        for name in reads(s):
            last[name] = k
    return last
