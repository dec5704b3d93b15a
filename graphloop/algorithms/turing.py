"""Turing machines as procedures: one join with the transition table per step, memory in proportion to the cells visited."""

from __future__ import annotations

from dataclasses import dataclass

from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import AskTrue, Procedure
from graphloop.plans.runtime import RunResult, run

BLANK = "_"


@dataclass(frozen=True)
class Machine:
    """``moves``: (state, read) to (state, write, step of the head); the machine halts where no move applies."""

    start: str
    accept: str
    moves: tuple  # of (state, read, new state, write, step)


PARITY = Machine("even", "even", (("even", "1", "odd", "1", 1), ("odd", "1", "even", "1", 1)))
INCREMENT = Machine("run", "done", (("run", "1", "run", "1", 1), ("run", BLANK, "done", "1", 0)))
BINARY_INCREMENT = Machine("carry", "done", (("carry", "1", "carry", "0", 1), ("carry", "0", "done", "1", 0), ("carry", BLANK, "done", "1", 0)))


def encode_word(word: str) -> q.Values:
    """The tape of a word: one (pos, symbol) per letter."""
    return q.Values(("pos", "symbol"), tuple((k, c) for k, c in enumerate(word)) or ((0, BLANK),))


def turing_procedure(machine: Machine, word: str) -> Procedure:
    """Runs until no move applies; returns the tape joined with the accepting state, so nothing if the word is rejected."""
    moves = q.Values(("state", "symbol", "new", "write", "step"), machine.moves)
    proc = Procedure().let("tape", encode_word(word)).let("moves", moves)
    proc.let("head", q.Values(("state", "pos"), ((machine.start, 0),)))
    at_head = q.Project(q.LeftJoin(q.VarRef("head"), q.VarRef("tape")), ("state", "pos", (q.call("coalesce", "?symbol", q.Const(BLANK)), "symbol")))
    body = Procedure().let("move", q.Join(at_head, q.VarRef("moves")))
    moved = q.Project(q.VarRef("move"), ((q.Var("new"), "state"), (q.call("+", "?pos", "?step"), "pos")))
    stay = q.Exists(q.VarRef("head"), q.VarRef("move"), negated=True)
    written = q.Project(q.VarRef("move"), ("pos", (q.Var("write"), "symbol")))
    rest = q.Exists(q.VarRef("tape"), q.Project(q.VarRef("move"), ("pos",)), negated=True)
    body.let("tape", q.Union(rest, written)).let("head", q.Union(moved, stay))
    none = q.Filter(q.Group(q.VarRef("move"), (), (("n", q.Agg("count")),)), q.call("=", "?n", 0))
    proc.loop(body, AskTrue(none))
    accepted = q.Project(q.Filter(q.VarRef("head"), q.call("=", "?state", q.Const(machine.accept))), ("state",))
    return proc.let("result", q.Project(q.Join(accepted, q.VarRef("tape")), ("pos", "symbol"))).ret("result")


def run_machine(machine: Machine, word: str, spark) -> RunResult:
    return run(turing_procedure(machine, word), Catalog(spark))
