"""Procedures: assignments, do-until loops and one final return."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

from graphloop.plans.query import Query, Table, references


@dataclass(frozen=True)
class Let:
    """Binds the result of ``query`` to ``var``. A ``lazy`` value in a loop is not snapshotted; ``split`` evaluates in batches."""

    var: str
    query: Query
    lazy: bool = False
    split: Any = None


@dataclass(frozen=True)
class Times:
    """Met once the body has run ``rounds`` times."""

    rounds: int


@dataclass(frozen=True)
class Fixpoint:
    """Met when ``var`` holds the same set of solutions as at the start of the round.

    ``check``: 'fingerprint', 'exact', or 'count' for sequences that are sets and only grow.
    """

    var: str
    check: str = "fingerprint"


@dataclass(frozen=True)
class FixpointWithin:
    """Met when no ``value`` moved by more than ``eps``, by key, and no key came or went."""

    var: str
    key: str
    value: str
    eps: float


@dataclass(frozen=True)
class AskTrue:
    """Met when the query has a solution."""

    query: Query


@dataclass(frozen=True)
class Until:
    """Met when ``test(env, env at the start of the round)`` is true."""

    test: Callable
    reads: tuple = ()


@dataclass(frozen=True)
class Loop:
    """Runs ``body`` until ``until`` is met, at least once. ``keys`` has (variable, column) by which variables are laid out."""

    body: tuple
    until: Any
    max_rounds: int | None = None
    guard: tuple = ()
    keys: tuple = ()


@dataclass(frozen=True)
class Return:
    var: str


class MalformedProcedure(ValueError):
    """A procedure that breaks a rule of the language."""


@dataclass
class Procedure:
    """A sequence of statements, built step by step."""

    statements: list = field(default_factory=list)

    def let(self, var: str, query, lazy: bool = False, reads: tuple = (), split=None) -> Procedure:
        """``query`` is algebra, a function of the environment, or SQL text over the variables in ``reads``."""
        if not isinstance(query, Query):
            query = Table(query, tuple(reads))
        self.statements.append(Let(var, query, lazy, split))
        return self

    def loop(self, body: Procedure | list, until, max_rounds: int | None = None, guard: tuple = (), keys: tuple = ()) -> Procedure:
        statements = body.statements if isinstance(body, Procedure) else body
        self.statements.append(Loop(tuple(statements), until, max_rounds, tuple(guard), tuple(keys)))
        return self

    def ret(self, var: str) -> Procedure:
        self.statements.append(Return(var))
        return self

    def include(self, other: Procedure, output: str) -> Procedure:
        """Runs another procedure's statements here; what it returns becomes ``output``."""
        from graphloop.plans.query import VarRef

        *body, last = other.statements
        self.statements += body
        self.statements.append(Let(output, VarRef(last.var), lazy=True))
        return self


def validate(proc: Procedure, strict: bool = True) -> list[str]:
    """What is wrong with a procedure; empty if nothing is.

    One return, at the end and not nested; positive round counts; and, if ``strict``, every
    variable that is read has been assigned in an earlier statement.
    """
    issues: list[str] = []
    if not proc.statements or not isinstance(proc.statements[-1], Return):
        issues.append("the last statement must be a return")

    def check(statements, assigned: set[str], top: bool) -> set[str]:
        for k, s in enumerate(statements):
            if isinstance(s, Return):
                if not top or k < len(statements) - 1:
                    issues.append(f"return of {s.var} is not the last statement")
                need(s.var, assigned, "return")
            elif isinstance(s, Let):
                for name in sorted(references(s.query)):
                    need(name, assigned, f"assignment of {s.var}")
                assigned = assigned | {s.var}
            elif isinstance(s, Loop):
                inside = check(s.body, assigned, False)
                c = s.until
                if isinstance(c, Times) and (not isinstance(c.rounds, int) or c.rounds < 1):
                    issues.append(f"a loop cannot run {c.rounds} times")
                if isinstance(c, (Fixpoint, FixpointWithin)):
                    need(c.var, inside, "fixpoint")
                if isinstance(c, AskTrue):
                    for name in sorted(references(c.query)):
                        need(name, inside, "condition")
                assigned = inside
            else:
                issues.append(f"not a statement: {s!r}")
        return assigned

    def need(name: str, assigned: set[str], where: str) -> None:
        if strict and name not in assigned:
            issues.append(f"{where} reads {name}, which has no value yet")

    check(proc.statements, set(), True)
    return issues
