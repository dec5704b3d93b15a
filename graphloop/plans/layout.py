"""What a loop reads, and the variable by which its statements join it: known before the first round."""

from __future__ import annotations

from collections import Counter

from graphloop.plans import query as q
from graphloop.plans.procedure import AskTrue, Let, Loop, Procedure, Until, references


def assigned(body) -> set[str]:
    """Variables that statements assign, nested ones too."""
    out: set[str] = set()
    for s in body:
        out |= {s.var} if isinstance(s, Let) else assigned(s.body) if isinstance(s, Loop) else set()
    return out


def loop_reads(loop: Loop) -> list[str]:
    """Variables whose value from before a round it may read, or its condition reads."""
    found: dict[str, None] = {}

    def look(body, done: set[str]) -> set[str]:
        for s in body:
            if isinstance(s, Let):
                found.update(dict.fromkeys(sorted(references(s.query) - done)))
                done = done | {s.var}
            elif isinstance(s, Loop):
                done = look(s.body, done)
        return done

    look(loop.body, set())
    if isinstance(loop.until, AskTrue):
        found.update(dict.fromkeys(sorted(references(loop.until.query))))
    if hasattr(loop.until, "var"):
        found[loop.until.var] = None
    if isinstance(loop.until, Until):
        found.update(dict.fromkeys(loop.until.reads))
    return list(found)


def read_often(proc: Procedure) -> set[str]:
    """Variables that the text reads twice or more: worth a snapshot, as each reading would evaluate them again."""
    times: Counter = Counter()

    def look(body) -> None:
        for s in body:
            if isinstance(s, Let):
                for node in q.walk(s.query):
                    times.update([node.name] if isinstance(node, q.VarRef) else node.reads if isinstance(node, q.Table) else ())
            elif isinstance(s, Loop):
                look(s.body)

    look(proc.statements)
    return {name for name, n in times.items() if n > 1}


def opaque(loop: Loop) -> bool:
    """Whether some statement of the loop does not say what it reads."""
    inside = [opaque(s) if isinstance(s, Loop) else any(isinstance(n, q.Table) and not n.reads for n in q.walk(s.query)) for s in loop.body]
    return any(inside)


def scope(node: q.Query, known: dict[str, frozenset]) -> frozenset:
    """Variables that a query's solutions have columns for; of what is not known, none."""
    if isinstance(node, q.VarRef):
        return known.get(node.name, frozenset())
    if isinstance(node, q.Pattern):
        return frozenset(t.name for t in (*node.ends(), q.term(node.p) if isinstance(node.p, (str, q.Var)) else None) if isinstance(t, q.Var))
    if isinstance(node, q.Project):
        return frozenset(i if isinstance(i, str) else i[1] for i in node.items)
    if isinstance(node, q.Group):
        return frozenset([*(k if isinstance(k, str) else k[1] for k in node.keys), *(name for name, _ in node.aggs)])
    if isinstance(node, q.Values):
        return frozenset(node.vars)
    if isinstance(node, (q.Minus, q.Exists, q.Filter, q.Distinct, q.Slice, q.GraphClause)):
        return scope(node.children()[0], known)
    if isinstance(node, q.Extend):
        return scope(node.body, known) | {node.var}
    return frozenset().union(*(scope(c, known) for c in node.children()))


def leaves(node: q.Query) -> list[q.Query]:
    """Operands of a tree of joins without hints."""
    if isinstance(node, q.Join) and node.hint is None:
        return [*leaves(node.left), *leaves(node.right)]
    return [node]


def origin(node: q.Query, known: dict[str, frozenset]) -> tuple[str, dict[str, str]] | None:
    """(variable, its query variables by the names they have here) of a part that renames, drops or groups what one variable holds."""
    if isinstance(node, q.VarRef):
        return node.name, {v: v for v in known.get(node.name, ())}
    if isinstance(node, (q.Project, q.Group)):
        below = origin(node.body, known)
        items = node.items if isinstance(node, q.Project) else node.keys
        named = [(i, i) if isinstance(i, str) else (i[0].name, i[1]) for i in items if isinstance(i, str) or isinstance(i[0], q.Var)]
        return below and (below[0], {new: below[1][old] for old, new in named if old in below[1]})
    return None


def join_keys(loop: Loop, known: dict[str, frozenset]) -> dict[str, str]:
    """For each variable with a value from before the loop, a query variable on which it is joined there."""
    wanted = set(loop_reads(loop))
    found: dict[str, str] = {}

    def look(body, known) -> dict[str, frozenset]:
        for s in body:
            if isinstance(s, Loop):
                known = look(s.body, known)
            elif isinstance(s, Let):
                for node in q.walk(s.query):
                    if isinstance(node, q.Join) and node.hint is None:
                        sides = leaves(node)
                    elif isinstance(node, (q.LeftJoin, q.Minus)):
                        sides = [node.left, node.right]
                    elif isinstance(node, q.Exists):
                        sides = [node.body, node.test]
                    else:
                        continue
                    for k, side in enumerate(sides):
                        held = origin(side, known)
                        if held and held[0] in wanted:
                            shared = scope(side, known) & frozenset().union(*(scope(x, known) for x in (*sides[:k], *sides[k + 1 :])))
                            sources = sorted(held[1][v] for v in shared if v in held[1])
                            if sources:
                                found.setdefault(held[0], sources[0])
                known = {**known, s.var: scope(s.query, known)}
        return known

    look(loop.body, known)
    return found
