"""Runs procedures: an environment of result variables, one snapshot per loop-carried assignment."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager, nullcontext
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from graphloop.materialize import checkpoint_files, discard, durable, has_hub, laid_out, parts_for, settings, steady
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.compiler import ask, compile_query
from graphloop.plans.layout import assigned, join_keys, loop_reads, opaque, read_often
from graphloop.plans.procedure import AskTrue, FixpointWithin, Let, Loop, MalformedProcedure, Procedure, Return, Times, Until, references, validate
from graphloop.relation import Relation, fingerprint, same_set

INLINE_ROWS = 5_000
LOG_PIECES = 6
# Batches are joined on their key too, by which nothing need be dealt where one of the other columns is that key.
_BY_PART_OF_KEY = {"spark.sql.requireAllClusterKeysForCoPartition": "false"}


class RoundLimit(RuntimeError):
    """A loop ran its full number of rounds without meeting its condition."""


class TimeLimit(RuntimeError):
    """A procedure took longer than it may."""


class InlineLimit(RuntimeError):
    """A sequence is too long to be written into a query as text."""


class StateCycle(RuntimeError):
    """The variables of a loop came back to an earlier state without meeting the condition."""


@dataclass
class RunResult:
    """The returned sequence, rounds of every loop in the order they ended, and a trace row per assignment."""

    relation: Relation
    rounds: list[int]
    trace: list[dict]
    env: dict[str, Relation] = field(default_factory=dict)

    @property
    def df(self) -> DataFrame:
        return self.relation.df


def snapshot(relation: Relation) -> Relation:
    """A reliable checkpoint of a relation that knows its number of rows; one job."""
    df = relation.df
    if not df.columns:
        return replace(relation, rows=df.count())
    seen = Observation()
    df = durable(df.observe(seen, F.count(F.lit(1)).alias("n")))
    return Relation(df, relation.maybe, seen.get["n"], kept=True)


@contextmanager
def time_limit(spark, seconds: float | None) -> Iterator[None]:
    """Cancels the Spark jobs of this thread that still run after ``seconds``, and raises ``TimeLimit`` for them."""
    if not seconds:
        yield
        return
    sc, group, late = spark.sparkContext, f"graphloop-{uuid.uuid4().hex}", threading.Event()
    kept = {name: sc.getLocalProperty(name) for name in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel")}
    done = threading.Event()

    def watch() -> None:
        if not done.wait(seconds):
            late.set()
            while not done.wait(0.5):  # jobs that start afterwards go too
                sc.cancelJobGroup(group)

    sc.setJobGroup(group, "a task with a time limit", interruptOnCancel=True)
    watcher = threading.Thread(target=watch, daemon=True)
    watcher.start()
    try:
        yield
        if late.is_set():
            raise TimeLimit(f"took more than {seconds} s")
    except TimeLimit:
        raise
    except Exception as problem:
        if late.is_set():
            raise TimeLimit(f"stopped after {seconds} s") from problem
        raise
    finally:
        done.set()
        watcher.join()
        for name, value in kept.items():
            sc.setLocalProperty(name, value)


def literal(relation: Relation, cap: int = INLINE_ROWS) -> tuple[Relation, int]:
    """The same solutions as constants in a query text, and the text's length."""
    rows = relation.df.limit(cap + 1).collect()
    if len(rows) > cap:
        raise InlineLimit(f"more than {cap} rows")
    spark = relation.df.sparkSession
    if not rows:
        return relation, 0
    kinds = dict(relation.df.dtypes)

    def value(v, kind: str) -> str:
        if v is None:
            return f"CAST(NULL AS {kind})"
        return f"CAST('{str(v).replace(chr(92), chr(92) * 2).replace(chr(39), chr(92) + chr(39))}' AS {kind})"

    names = ", ".join(f"`{c}`" for c in relation.vars)
    text = ", ".join("(" + ", ".join(value(r[c], kinds[c]) for c in relation.vars) + ")" for r in rows)
    text = f"SELECT * FROM VALUES {text} AS t({names})"
    return Relation(spark.sql(text), relation.maybe, len(rows)), len(text)


class _Run:
    """Evaluation of one procedure.

    A value that is read once is part of the plan that reads it; one that is read more often, or in
    the next round, is a snapshot.

    What a loop reads is snapshotted before its first round, and laid out by the variable that
    its statements join it on. Within a loop plans are steady (``materialize.steady``) unless
    one value of that variable holds too many rows; then adaptive plans stay on, which split
    such a value. A statement that only adds to a variable keeps a log of snapshots. Snapshots that no
    variable's plan reads any more are deleted after each round.
    """

    def __init__(self, catalog: Catalog, mode: str, max_rounds: int, deadline: float | None, inline_rows: int):
        self.catalog, self.mode, self.max_rounds, self.deadline, self.inline_rows = catalog, mode, max_rounds, deadline, inline_rows
        self.env: dict[str, Relation] = {}
        self.rounds: list[int] = []
        self.trace: list[dict] = []
        self.number = 0
        self.logs: dict[str, list[Relation]] = {}
        self.made: set[str] = set()
        self.prints: dict[str, tuple] = {}
        self.shared: set[str] = set()
        self.carried: set[str] = set()

    def statements(self, body, in_loop: bool, round_: int = 0) -> None:
        for s in body:
            if isinstance(s, Let):
                self.let(s, in_loop, round_)
            elif isinstance(s, Loop):
                self.loop(s)

    def keep(self, relation: Relation) -> Relation:
        return self.noted(snapshot(relation))

    def noted(self, found: Relation) -> Relation:
        if not found.vars:
            return found
        files = checkpoint_files(found.df)
        self.made |= files
        return replace(found, files=files)

    def let(self, s: Let, in_loop: bool, round_: int) -> None:
        began = time.time()
        text, batches = 0, 0
        env = self.env
        if self.mode == "inline":
            env = dict(env)
            for name in references(s.query):
                if name in env:
                    env[name], n = literal(env[name], self.inline_rows)
                    text += n
        log = None
        if s.split is not None and self.mode == "batched":
            found, batches = s.split.evaluate(s.query, env, self.catalog)
        elif self.mode == "plan" and in_loop and (more := _added(s)) is not None and s.var in env:
            found = compile_query(more, env, self.catalog)
            if sorted(found.vars) == sorted(env[s.var].vars):
                found = found if found.kept else self.keep(found)
                log = self.logged(s.var, found)
                found = self.joined(log)
            else:
                found = compile_query(s.query, env, self.catalog)
        else:
            found = compile_query(s.query, env, self.catalog)
        if log is None and not found.kept and found.vars and ((s.var in self.carried or s.var in self.shared) and not s.lazy or self.mode != "plan"):
            found = self.keep(found)
        elif log is None and not found.kept:
            unknown = any(isinstance(n, q.Table) and callable(n.make) and not n.reads for n in q.walk(s.query))
            names = self.env if unknown else references(s.query) & self.env.keys()
            found = replace(found, files=frozenset().union(*(self.env[n].files for n in names)))
        self.logs = {k: v for k, v in self.logs.items() if k != s.var} | ({s.var: log} if log else {})
        self.env = {**self.env, s.var: found}
        self.number += 1
        self.trace.append({"step": self.number, "var": s.var, "round": round_, "rows": found.rows, "ms": round((time.time() - began) * 1000), "text": text, "batches": batches, "mode": self.mode})

    # Logs: a variable that only grows is a bounded number of snapshots, merged when they are too many.

    def logged(self, var: str, found: Relation) -> list[Relation]:
        old = self.env[var]
        pieces = self.logs.get(var) or [old if old.kept else self.keep(old)]
        if found.rows == 0:
            return pieces
        pieces = [*pieces, found]
        if len(pieces) > LOG_PIECES:
            top = max(range(len(pieces)), key=lambda k: pieces[k].rows)
            rest = [x for k, x in enumerate(pieces) if k != top]
            if sum(x.rows for x in rest) * 2 > pieces[top].rows:
                return [self.keep(self.joined(pieces))]
            return [pieces[top], self.keep(self.joined(rest))]
        return pieces

    @staticmethod
    def joined(pieces: list[Relation]) -> Relation:
        if len(pieces) == 1:
            return pieces[0]
        df = reduce(lambda a, b: a.unionByName(b), (x.df for x in pieces))
        return Relation(df, frozenset().union(*(x.maybe for x in pieces)), sum(x.rows for x in pieces), files=frozenset().union(*(x.files for x in pieces)))

    def sweep(self) -> None:
        """Deletes snapshots of this run that no value reads."""
        live = frozenset().union(*(r.files for r in self.env.values()), *(r.files for log in self.logs.values() for r in log))
        dead = self.made - live
        if dead:
            discard(self.catalog.spark, dead)
            self.made -= dead

    def pin(self, s: Loop) -> int | None:
        """Snapshots what the loop reads; the partitions of a steady loop, or None where plans must adapt."""
        wanted = [n for n in loop_reads(s) if n in self.env]
        for name in wanted:
            r = self.env[name]
            if r.vars and not r.kept:
                self.env = {**self.env, name: self.keep(r)}
        spark = self.catalog.spark
        parts = parts_for(spark, max((self.env[n].rows or 0 for n in wanted), default=0))
        if opaque(s):
            return None
        keys = join_keys(s, {n: frozenset(r.vars) for n, r in self.env.items()}) | dict(s.keys)
        plain = [n for n in wanted if self.env[n].vars and n in keys]
        if any(has_hub(self.env[n].df, keys[n], self.env[n].rows, parts) for n in plain):
            return None
        for name in wanted:
            r = self.env[name]
            if r.vars and (parts == 1 or name in keys):
                self.env = {**self.env, name: self.noted(replace(r, df=laid_out(r.df, keys.get(name), parts)))}
        return parts

    def loop(self, s: Loop) -> None:
        limit = s.max_rounds or self.max_rounds
        rounds, seen, power, lap = 0, None, 1, 0
        spark = self.catalog.spark
        parts = self.pin(s) if self.mode != "inline" else None
        outer = self.carried
        self.carried = outer | (assigned(s.body) if opaque(s) or s.guard else set(loop_reads(s)))
        while True:
            before = self.env
            rounds += 1
            with settings(spark, steady(parts) | _BY_PART_OF_KEY) if parts else nullcontext():
                self.statements(s.body, True, rounds)
                met = self.met(s.until, before, rounds)
            self.sweep()
            if met:
                break
            if parts:
                parts = max(parts, parts_for(spark, max((r.rows or 0 for n, r in self.env.items()), default=0)))
            if self.deadline and time.time() > self.deadline:
                raise TimeLimit(f"stopped after {rounds} rounds")
            if rounds >= limit:
                raise RoundLimit(f"condition not met in {rounds} rounds")
            if s.guard:  # Brent: compare with the state at the last power of two
                state = tuple(fingerprint(self.env[v].df) for v in s.guard)
                if state == seen:
                    raise StateCycle(f"round {rounds} repeats an earlier state")
                lap += 1
                if lap == power:
                    seen, power, lap = state, power * 2, 0
        self.carried = outer
        self.rounds.append(rounds)

    def print_of(self, var: str, relation: Relation):
        held = self.prints.get(var)
        return held[1] if held and held[0] is relation else fingerprint(relation.df)

    def met(self, c, before: dict[str, Relation], rounds: int) -> bool:
        if isinstance(c, Times):
            return rounds >= c.rounds
        if isinstance(c, AskTrue):
            empty = _asks_for_nothing(c.query)
            if empty in self.env and self.env[empty].rows is not None:
                return self.env[empty].rows == 0
            return ask(c.query, self.env, self.catalog)
        if isinstance(c, Until):
            return c.test(self.env, before)
        old, new = before.get(c.var), self.env[c.var]
        if isinstance(c, FixpointWithin):
            if old is None or old.rows is not None and new.rows is not None and old.rows != new.rows:
                return False
            a = old.df.select(F.col(c.key).alias("k"), F.col(c.value).alias("x"))
            b = new.df.select(F.col(c.key).alias("k"), F.col(c.value).alias("y"))
            moved = a.join(b, "k", "full").where(F.coalesce(F.abs(F.col("x") - F.col("y")) > c.eps, F.lit(True)))
            return moved.isEmpty()
        if old is None:
            return new.df.isEmpty()
        if c.check == "count":
            return old.rows is not None and old.rows == new.rows or (old.df.count() == new.df.count())
        if c.check == "exact":
            return same_set(old.df, new.df)
        if sorted(old.vars) != sorted(new.vars):
            return False
        a, b = self.print_of(c.var, old), fingerprint(new.df)
        self.prints[c.var] = (new, b)
        return a == b


def _added(s: Let) -> q.Query | None:
    """What a statement adds to its variable, if that is all it does."""
    body = s.query
    if isinstance(body, q.Union):
        for own, more in ((body.left, body.right), (body.right, body.left)):
            if own == q.VarRef(s.var) and s.var not in references(more):
                return more
    return None


def _asks_for_nothing(query: q.Query) -> str | None:
    """The variable x of a condition that counts the solutions of x and compares the number with 0."""
    query = query.body if isinstance(query, q.Ask) else query
    if not isinstance(query, q.Filter) or not isinstance(query.condition, q.Call) or query.condition.fn != "=":
        return None
    counted, zero = query.condition.args
    body, names = query.body, {}
    if isinstance(body, q.Project):
        names = {i[1]: i[0] for i in body.items if not isinstance(i, str)}
        body = body.body
    counted = names.get(getattr(counted, "name", None), counted)
    plain = isinstance(body, q.Group) and not body.keys and body.having is None and isinstance(body.body, q.VarRef)
    if plain and zero == q.Const(0) and body.aggs == ((getattr(counted, "name", None), q.Agg("count")),):
        return body.body.name
    return None


def run(
    proc: Procedure,
    catalog: Catalog,
    mode: str = "plan",
    strict: bool = True,
    max_rounds: int = 10_000,
    timeout_s: float | None = None,
    inline_rows: int = INLINE_ROWS,
    env: dict[str, Relation] | None = None,
) -> RunResult:
    """Runs a procedure. ``mode``: 'plan' refers to results as plans, 'inline' writes them into queries, 'batched' splits where a statement says how.

    After ``timeout_s`` its jobs are cancelled. Variables have global scope. Not ``strict``, a variable that is read before it has a value holds no solutions.
    """
    issues = validate(proc, strict)
    if issues:
        raise MalformedProcedure("; ".join(issues))
    if mode not in ("plan", "inline", "batched"):
        raise ValueError(f"unknown mode {mode!r}")
    state = _Run(catalog, mode, max_rounds, time.time() + timeout_s if timeout_s else None, inline_rows)
    state.env = dict(env or {})
    *body, last = proc.statements
    state.shared = read_often(proc)
    with time_limit(catalog.spark, timeout_s):
        state.statements(body, False)
    assert isinstance(last, Return)
    return RunResult(state.env[last.var], state.rounds, state.trace, state.env)


def is_nonempty(proc: Procedure, catalog: Catalog, **options) -> bool:
    """The evaluation problem: whether a procedure returns any solution."""
    return not run(proc, catalog, **options).df.isEmpty()


def contains_answer(proc: Procedure, catalog: Catalog, answer: dict, **options) -> bool:
    """Whether one of the returned solutions has the given values."""
    df = run(proc, catalog, **options).df
    for name, value in answer.items():
        df = df.where(F.col(name) == F.lit(value))
    return not df.isEmpty()


def empty_relation(catalog: Catalog, schema: str) -> Relation:
    """No solutions over the variables of a schema."""
    return Relation(catalog.spark.createDataFrame([], schema), rows=0)


def as_values(relation: Relation) -> q.Values:
    """A small relation as a data block."""
    rows, names = relation.df.collect(), relation.vars
    return q.Values(tuple(names), tuple(tuple(r) for r in rows))
