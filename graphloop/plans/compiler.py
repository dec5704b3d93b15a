"""From algebra to DataFrames."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.functions.scalar import column, variables
from graphloop.materialize import durable
from graphloop.operators import compat
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.relation import Relation


def unit(catalog: Catalog) -> Relation:
    """One solution without variables."""
    return Relation(catalog.spark.range(1).select(), rows=1)


def compile_query(query: q.Query, env: dict[str, Relation], catalog: Catalog) -> Relation:
    """The relation of a query over the result variables in ``env`` and the graph of ``catalog``."""
    return _Compiler(env, catalog).build(query)


_TOTAL = {"=", "!=", "<", "<=", ">", ">=", "&&", "||", "!", "if", "bound"}


def _sure(value, body: Relation) -> bool:
    """Whether an expression has a value in every solution, as far as its form tells."""
    if isinstance(value, q.Const):
        return value.value is not None
    if isinstance(value, q.Var):
        return value.name in body.vars and value.name not in body.maybe
    if value.fn.lower() == "coalesce":
        return any(_sure(a, body) for a in value.args)
    return value.fn.lower() in _TOTAL and (value.fn.lower() == "bound" or all(_sure(a, body) for a in value.args))


class _Compiler:
    def __init__(self, env: dict[str, Relation], catalog: Catalog):
        self.env, self.catalog = env, catalog

    def build(self, node: q.Query) -> Relation:
        return getattr(self, "_" + type(node).__name__.lower())(node)

    def _unit(self, node) -> Relation:
        return unit(self.catalog)

    # Patterns and paths

    def _pattern(self, node: q.Pattern) -> Relation:
        s, o = node.ends()
        p = node.p
        if isinstance(p, str) and p.startswith("?"):
            p = q.Var(p[1:])
        if isinstance(p, q.Var):
            return self._bind(self.catalog.triples(), [("s", s), ("p", p), ("o", o)])
        return self._bind(self._path(p), [("s", s), ("o", o)])

    def _bind(self, df: DataFrame, slots) -> Relation:
        """Constants and repeated variables filter, variables name the columns."""
        seen: dict[str, str] = {}
        for name, t in slots:
            df = df.where(F.col(name).isNotNull())
            if isinstance(t, q.Const):
                df = df.where(F.col(name) == F.lit(t.value))
            elif t.name in seen:
                df = df.where(F.col(name) == F.col(seen[t.name]))
            else:
                seen[t.name] = name
        return Relation(df.select(*(F.col(name).alias(v) for v, name in seen.items())))

    def _path(self, p) -> DataFrame:
        if isinstance(p, str):
            return self.catalog.pairs(p)
        if isinstance(p, q.Step):
            df = self.catalog.pairs(p.name)
            return df.select(F.col("o").alias("s"), F.col("s").alias("o")) if p.inverse else df
        if isinstance(p, q.Seq):
            return reduce(lambda a, b: _compose(a, self._path(b)), p.parts[1:], self._path(p.parts[0]))
        if isinstance(p, q.Alt):
            return reduce(DataFrame.unionByName, [self._path(x) for x in p.parts])
        if isinstance(p, q.Negated):
            names = [n for n in self.catalog.predicates if n not in p.names]
            t = self.catalog.triples(names)
            return t.select("s", "o")
        if isinstance(p, q.Repeat):
            step = self._path(p.part).where("s is not null and o is not null").distinct()
            out = step if p.most == 1 else closure(step)
            if p.least == 0:
                ends = step.select(F.col("s").alias("x")).union(step.select("o")).distinct()
                out = out.union(ends.select(F.col("x").alias("s"), F.col("x").alias("o"))).distinct()
            return out
        raise TypeError(f"not a path: {p!r}")

    def _bgp(self, node: q.Bgp) -> Relation:
        """Joins of patterns; patterns of one subject and one table are read by a single scan."""
        stars: dict = {}
        parts: list[Relation] = []
        for p in node.patterns:
            name = p.p if isinstance(p.p, str) and not p.p.startswith("?") else None
            known = self.catalog.predicates.get(name) if name else None
            subject = q.term(p.s)
            if known and known.source and known.source != "lineitem" and isinstance(subject, q.Var):
                stars.setdefault((known.source, subject.name), []).append(p)
            else:
                parts.append(self._pattern(p))
        for (_, subject), patterns in stars.items():
            parts.append(self._star(subject, patterns))
        return reduce(self._join_connected, self._ordered(parts))

    def _star(self, subject: str, patterns: list[q.Pattern]) -> Relation:
        preds = [self.catalog.predicates[p.p] for p in patterns]
        if len(patterns) == 1 or any(str(x.subject) != str(preds[0].subject) for x in preds):
            return reduce(compat.join, [self._pattern(p) for p in patterns])
        columns = [preds[0].subject.alias("_s")] + [x.object.alias(f"_o{k}") for k, x in enumerate(preds)]
        df = preds[0].table().select(*columns)
        slots = [("_s", q.Var(subject))] + [(f"_o{k}", p.ends()[1]) for k, p in enumerate(patterns)]
        return self._bind(df, slots)

    def _ordered(self, parts: list[Relation]) -> list[Relation]:
        """Parts so that each shares a variable with those before, where that is possible."""
        todo, out, seen = list(parts), [], set()
        while todo:
            pick = next((r for r in todo if seen & set(r.vars)), todo[0])
            todo = [r for r in todo if r is not pick]
            out.append(pick)
            seen |= set(pick.vars)
        return out

    @staticmethod
    def _join_connected(a: Relation, b: Relation) -> Relation:
        return compat.join(a, b)

    # Algebra

    def _join(self, node: q.Join) -> Relation:
        return compat.join(self.build(node.left), self.build(node.right), node.hint)

    def _leftjoin(self, node: q.LeftJoin) -> Relation:
        condition = None
        if node.condition is not None:
            condition = lambda both: column(node.condition, set(both.vars))
        return compat.left_join(self.build(node.left), self.build(node.right), condition)

    def _minus(self, node: q.Minus) -> Relation:
        return compat.minus(self.build(node.left), self.build(node.right))

    def _union(self, node: q.Union) -> Relation:
        return compat.union(self.build(node.left), self.build(node.right))

    def _filter(self, node: q.Filter) -> Relation:
        body = self.build(node.body)
        # A comparison that is true has bound its variables.
        bound = variables(node.condition) if isinstance(node.condition, q.Call) and node.condition.fn in ("=", "<", ">", "<=", ">=", "!=", "in") else set()
        return Relation(body.df.where(column(node.condition, set(body.vars))), body.maybe - bound)

    def _exists(self, node: q.Exists) -> Relation:
        return compat.exists(self.build(node.body), self.build(node.test), node.negated)

    def _extend(self, node: q.Extend) -> Relation:
        body = self.build(node.body)
        if node.var in body.vars:
            raise ValueError(f"?{node.var} is already in scope")
        value = q.expr(node.value)
        return Relation(body.df.withColumn(node.var, column(value, set(body.vars))), body.maybe | (frozenset() if _sure(value, body) else {node.var}), body.rows)

    def _values(self, node: q.Values) -> Relation:
        names = list(node.vars)
        maybe = frozenset(n for k, n in enumerate(names) if any(r[k] is None for r in node.rows))
        if not node.rows:
            return Relation(self.catalog.spark.createDataFrame([], ", ".join(f"`{n}` long" for n in names)))
        return Relation(self.catalog.spark.createDataFrame([tuple(r) for r in node.rows], names), maybe, len(node.rows))

    def _varref(self, node: q.VarRef) -> Relation:
        if node.name not in self.env:
            raise KeyError(f"result variable {node.name!r} has no value")
        return self.env[node.name]

    def _project(self, node: q.Project) -> Relation:
        body = self.build(node.body)
        columns, maybe = [], set()
        for item in node.items:
            value, name = (q.Var(item), item) if isinstance(item, str) else (q.expr(item[0]), item[1])
            # An alias that changes nothing would hide how a snapshot lies from what reads it.
            same = isinstance(value, q.Var) and value.name == name and name in body.vars
            columns.append(F.col(f"`{name}`") if same else column(value, set(body.vars)).alias(name))
            if not _sure(value, body):
                maybe.add(name)
        return Relation(body.df.select(*columns), frozenset(maybe), body.rows)

    def _distinct(self, node: q.Distinct) -> Relation:
        body = self.build(node.body)
        return Relation(body.df.distinct(), body.maybe)

    def _group(self, node: q.Group) -> Relation:
        body = self.build(node.body)
        known = set(body.vars)
        keys = [(q.Var(k), k) if isinstance(k, str) else (q.expr(k[0]), k[1]) for k in node.keys]
        aggs = [self._aggregate(a, known).alias(name) for name, a in node.aggs]
        key_columns = [column(e, known).alias(name) for e, name in keys]
        df = body.df.groupBy(*key_columns).agg(*aggs) if keys else body.df.agg(*aggs)
        if not keys:  # over nothing, sums, counts and means are 0
            zero = {name: F.coalesce(F.col(name), F.lit(0)) for name, a in node.aggs if a.fn in ("count", "sum", "avg")}
            df = df.withColumns(zero) if zero else df
        sure = {name for name, a in node.aggs if a.fn == "count" or not keys and a.fn in ("sum", "avg")}
        least = ("min", "max", "sample")  # over a group, these are bound where their variable is
        sure |= {name for name, a in node.aggs if keys and a.fn in least and isinstance(q.expr(a.arg), q.Var) and q.expr(a.arg).name in known - body.maybe}
        sure |= {name for e, name in keys if _sure(e, body)}
        names = [name for _, name in keys] + [name for name, _ in node.aggs]
        out = Relation(df, frozenset(n for n in names if n not in sure), None if keys else 1)
        if node.having is not None:
            out = Relation(out.df.where(column(node.having, set(names))), out.maybe)
        return out

    @staticmethod
    def _aggregate(a: q.Agg, known: set[str]):
        arg = F.lit(1) if a.arg is None else column(q.expr(a.arg), known)
        if a.fn == "count":
            return F.count_distinct(arg) if a.distinct else F.count(arg)
        if a.fn in ("sum", "avg") and a.distinct:
            return {"sum": F.sum_distinct(arg), "avg": F.try_divide(F.sum_distinct(arg), F.count_distinct(arg))}[a.fn]
        if a.fn == "group_concat":
            return F.array_join(F.array_sort(F.collect_set(arg.cast("string")) if a.distinct else F.collect_list(arg.cast("string"))), " ")
        return {"sum": F.try_sum, "avg": F.try_avg, "min": F.min, "max": F.max, "sample": F.min}[a.fn](arg)

    def _slice(self, node: q.Slice) -> Relation:
        body = self.build(node.body)
        df = body.df
        if node.order:
            keys = [(column(q.expr(e), set(body.vars)), down) for e, down in node.order]
            df = df.orderBy(*(k.desc_nulls_last() if down else k.asc_nulls_first() for k, down in keys))
        if node.offset:
            df = df.offset(node.offset)
        return Relation(df.limit(node.limit) if node.limit is not None else df, body.maybe)

    def _graphclause(self, node: q.GraphClause) -> Relation:
        return _Compiler(self.env, self.catalog.graphs[node.name]).build(node.body)

    def _ask(self, node: q.Ask) -> Relation:
        body = self.build(node.body).df
        return Relation(body.limit(1).agg((F.count(F.lit(1)) > 0).alias("ask")), rows=1)

    def _construct(self, node: q.Construct) -> Relation:
        body = self.build(node.body)
        known, parts = set(body.vars), []
        for triple in node.template:
            columns = [column(q.term(t), known).cast("string").alias(n) for t, n in zip(triple, "spo", strict=True)]
            parts.append(body.df.select(*columns).where("s is not null and p is not null and o is not null"))
        return Relation(reduce(DataFrame.union, parts).distinct())

    def _table(self, node: q.Table) -> Relation:
        if callable(node.make):
            out = node.make(self.env)
        else:
            out = self.catalog.spark.sql(node.make, **{name: self.env[name].df for name in node.reads})
        return out if isinstance(out, Relation) else Relation.of(out)


def _compose(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("s", F.col("o").alias("m")).join(b.select(F.col("s").alias("m"), "o"), "m").select("s", "o")


SLICED_EDGES = 1_000_000
SLICE_BYTES = 32_000_000
SLICE_TARGETS = 512
CELLS = 2_000_000


def closure(step: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """All pairs joined by one step or more.

    Up to ``SLICED_EDGES`` steps between whole numbers go to every task, which finds who reaches its slice of the targets. Beyond
    that, each round extends the pairs found in the last.
    """
    step = durable(step)
    whole = all(kind in ("bigint", "int") for _, kind in step.dtypes)
    if whole and step.where("s is null or o is null").isEmpty() and step.count() <= SLICED_EDGES:
        return _sliced_closure(step)
    known = new = step
    for _ in range(max_rounds):
        found = _compose(new, step).distinct()
        new = durable(found.join(known, ["s", "o"], "left_anti"))
        if new.isEmpty():
            return known
        known = known.union(new)
    raise RuntimeError(f"no fixpoint after {max_rounds} rounds")


@dataclass(frozen=True)
class _Steps:
    """A graph whose cycles are contracted to groups.

    Groups are numbered part by part of the graph, in each part those that reach little first; nodes lie in the order of their groups.
    """

    ids: np.ndarray  # the node at each place
    group: np.ndarray  # its group
    level: np.ndarray  # of a group: the most steps that can be gone from it
    until: np.ndarray  # of a group: the first group after its part of the graph
    cyclic: np.ndarray  # of a group: whether its nodes reach themselves
    src: np.ndarray  # steps between groups, in order
    dst: np.ndarray


def _contracted(s: np.ndarray, o: np.ndarray) -> _Steps:
    """The graph of the steps from ``s`` to ``o``, by one depth-first search."""
    nodes, at = np.unique(np.stack([s, o]), return_inverse=True)
    n, (src, dst) = len(nodes), at.reshape(2, -1)
    heads = dst[np.argsort(src, kind="stable")].tolist()
    ends = np.cumsum(np.bincount(src, minlength=n)).tolist()
    todo = [0, *ends[:-1]] if n else []
    seen, low, group = [-1] * n, [0] * n, [-1] * n
    opened: list[int] = []
    groups = count = 0
    for root in range(n):
        path = [root] if seen[root] < 0 else []
        while path:
            v = path[-1]
            if seen[v] < 0:
                seen[v] = low[v] = count
                count += 1
                opened.append(v)
            k = todo[v]
            while k < ends[v]:
                w = heads[k]
                if seen[w] < 0:  # the step is looked at again when all behind it is known
                    path.append(w)
                    break
                if group[w] < 0 and low[w] < low[v]:
                    low[v] = low[w]
                k += 1
            todo[v] = k
            if path[-1] != v:
                continue
            path.pop()
            if low[v] == seen[v]:
                while group[v] < 0:
                    group[opened.pop()] = groups
                groups += 1
    # What a group steps to has a smaller number.
    of = np.array(group, dtype=np.int64)
    a, b = of[src], of[dst]
    cyclic = np.zeros(groups, dtype=bool)
    cyclic[a[a == b]] = True
    between = np.unique(a[a != b] * groups + b[a != b])
    a, b = between // max(groups, 1), between % max(groups, 1)
    level, part = [0] * groups, list(range(groups))

    def top(g: int) -> int:
        while part[g] != g:
            part[g] = g = part[part[g]]
        return g

    for g, h in zip(a.tolist(), b.tolist(), strict=True):
        if level[h] >= level[g]:
            level[g] = level[h] + 1
        part[top(g)] = top(h)
    levels, parts = np.array(level, dtype=np.int64), np.array([top(g) for g in range(groups)], dtype=np.int64)
    size = np.bincount(parts, minlength=groups)
    order = np.lexsort((levels, parts, -size[parts]))  # large parts first
    place = np.empty(groups, dtype=np.int64)
    place[order] = np.arange(groups)
    last = np.flatnonzero(np.diff(parts[order], append=-1)) + 1
    until = np.repeat(last, np.diff(last, prepend=0))
    by = np.argsort(place[of], kind="stable")
    a, b = place[a], place[b]
    steps = np.lexsort((b, a))
    return _Steps(nodes[by], place[of][by], levels[order], until, cyclic[order], a[steps], b[steps])


def _slices(graph: _Steps, tasks: int) -> list[tuple[int, int]]:
    """(first, number) of targets; a row of bits for each group that may reach them makes ``SLICE_BYTES`` at most."""
    n, first, out = len(graph.ids), 0, []
    share = max(-(-n // tasks), SLICE_TARGETS)
    while first < n:
        many = min(share, n - first)
        rows = int(graph.until[graph.group[first + many - 1]] - graph.group[first])
        many = max(min(many, SLICE_BYTES * 8 // rows), 1)
        out.append((first, many))
        first += many
    return out


def _reaching(graph: _Steps, first: int, many: int) -> Iterator[pa.RecordBatch]:
    """(s, o): the nodes that reach any of a slice of targets, each with all those that it reaches."""
    low, high = int(graph.group[first]), int(graph.until[graph.group[first + many - 1]])
    words = -(-many // 64)
    held = np.zeros((high - low, words), dtype=np.uint64)
    bits = held.view(np.uint8)
    k = np.arange(many)
    np.bitwise_or.at(bits, (graph.group[first : first + many] - low, k >> 3), (128 >> (k & 7)).astype(np.uint8))
    # Level by level, groups take over the bits of what they step to.
    e, f = np.searchsorted(graph.src, [low, high])
    x, y = graph.src[e:f] - low, graph.dst[e:f] - low
    x, y = x[y >= 0], y[y >= 0]
    by = np.argsort(graph.level[low:high][x], kind="stable")
    x, y = x[by], y[by]
    if len(x):
        starts = np.flatnonzero(np.diff(x, prepend=-1))
        levels = np.flatnonzero(np.diff(graph.level[low:high][x], prepend=-1))
        cuts = np.union1d(levels, np.arange(0, len(x), max(SLICE_BYTES // (8 * words), 1)))
        ends = np.append(cuts[1:], len(x))
        since, before = np.searchsorted(starts, cuts, "right") - 1, np.searchsorted(starts, ends)
        owner = x[starts]
        for e, f, p, q in zip(cuts.tolist(), ends.tolist(), since.tolist(), before.tolist(), strict=True):
            held[owner[p:q]] |= np.bitwise_or.reduceat(held[y[e:f]], np.maximum(starts[p:q] - e, 0), axis=0)
    rows = max(CELLS // many, 1)
    targets = np.tile(graph.ids[first : first + many], rows)
    begin, end = np.searchsorted(graph.group, [low, high])
    for at in range(begin, end, rows):
        group = graph.group[at : min(at + rows, end)]
        found = bits[group - low]
        k = np.arange(max(at, first), min(at + len(group), first + many))
        k = k[~graph.cyclic[graph.group[k]]]  # these do not reach themselves
        found[k - at, (k - first) >> 3] &= ~(128 >> ((k - first) & 7)).astype(np.uint8)
        number = np.bitwise_count(found.view(np.uint64)).sum(axis=1, dtype=np.int64)
        some = number > 0
        if some.any():
            cells = np.unpackbits(found[some], axis=1, count=many).view(bool).reshape(-1)
            offsets = np.concatenate([[0], np.cumsum(number[some])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(targets[: len(cells)][cells]))
            yield pa.RecordBatch.from_arrays([pa.array(graph.ids[at : at + len(group)][some]), lists], names=["s", "o"])


def _sliced_closure(step: DataFrame) -> DataFrame:
    """The closure by rows of bits: for a slice of the targets, which of them each node of their part of the graph reaches.

    What a node reaches leaves Python as one list, as single rows cost several times as much on the way.
    """
    spark = step.sparkSession
    held = step.distinct().toArrow()
    graph = _contracted(*(held.column(c).to_numpy().astype(np.int64) for c in ("s", "o")))
    slices = _slices(graph, 8 * spark.sparkContext.defaultParallelism)
    shared = spark.sparkContext.broadcast((graph, slices))

    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph, slices = shared.value
        for batch in batches:
            for k in batch.column(0).to_pylist():
                yield from _reaching(graph, *slices[k])

    found = spark.range(0, len(slices), 1, max(len(slices), 1)).mapInArrow(reach, "s long, o array<long>")
    return found.select("s", F.explode("o").alias("o")).select(*(F.col(c).cast(kind).alias(c) for c, kind in step.dtypes))


def ask(query: q.Query, env: dict[str, Relation], catalog: Catalog) -> bool:
    """Whether a query has a solution. Runs a job that stops at the first."""
    body = query.body if isinstance(query, q.Ask) else query
    return not compile_query(body, env, catalog).df.isEmpty()
