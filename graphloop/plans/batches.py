"""Evaluation in batches: split the sequences a query reads by the values of a variable, evaluate, merge.

Three ways to evaluate: one query per value, as the method is defined; one query per hash
bucket of values, which bounds memory with few queries; and all batches in one query that
carries the value as a further key (lifted), which is the one for large domains.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.materialize import durable
from graphloop.operators import compat
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.compiler import compile_query
from graphloop.relation import Relation

KEY = "__c"
REPLICATED_ROWS = 1_000_000


def split_domain(rels: list[Relation], v: str) -> DataFrame:
    """(c): all values that any of the sequences binds to ``v``."""
    parts = [r.df.select(F.col(v).alias("c")).where("c is not null") for r in rels if v in r.vars]
    return reduce(DataFrame.union, parts).distinct() if parts else rels[0].df.sparkSession.createDataFrame([], "c long")


@dataclass(frozen=True)
class SplitPlan:
    """Keyed sub-sequences by name, with the rule that made each; the domain of values."""

    parts: dict[str, Relation]
    rules: dict[str, int]
    domain: DataFrame


def _inner_pairs(inner: list[q.Query], v: str, domain: DataFrame, catalog: Catalog) -> dict[str, DataFrame]:
    """For each inner query the pairs (__c, value of its variable), for all values of the domain at once."""
    out = {}
    for query in inner:
        answers = compile_query(query, {}, catalog).df
        (name,) = [c for c in answers.columns if c != v]
        pairs = answers.select(F.col(v).alias(KEY), F.col(name)).join(domain.select(F.col("c").alias(KEY)), KEY).distinct()
        out[name] = pairs
    return out


def map_split(rels: dict[str, Relation], v: str, inner: list[q.Query], catalog: Catalog, combine: str = "any") -> SplitPlan:
    """Splits each sequence by the values c of ``v``; the batch key is the column ``__c``.

    1. A sequence that binds ``v`` keeps, for c, its rows with v = c (rows that leave it unbound vanish).
    2. Otherwise, if it binds variables of inner queries, the rows with any (or ``all``) of
       them among the inner answers for c.
    3. Otherwise the whole sequence goes to every batch; it must be small, which is checked.

    Inner queries project their variable and ``v``, which stands for c.
    """
    if combine not in ("any", "all"):
        raise ValueError("combine is 'any' or 'all'")
    bound = {n for n, r in rels.items() if v in r.vars and (v not in r.maybe or not r.df.where(F.col(v).isNotNull()).isEmpty())}
    domain = split_domain(list(rels.values()), v)
    if inner or len(bound) < len(rels):  # else no part is made from it
        domain = durable(domain)
    pairs = _inner_pairs(inner, v, domain, catalog)
    parts, rules = {}, {}
    for name, r in rels.items():
        if name in bound:
            parts[name] = Relation(r.df.where(F.col(v).isNotNull()).withColumn(KEY, F.col(v)), r.maybe - {v})
            rules[name] = 1
            continue
        mine = [x for x in pairs if x in r.vars]
        if mine:
            if len(mine) == 1:
                df = r.df.join(pairs[mine[0]], mine[0])
            elif combine == "all":
                df = reduce(lambda d, x: d.join(pairs[x], [KEY, x]), mine[1:], r.df.join(pairs[mine[0]], mine[0]))
            else:
                numbered = durable(r.df.withColumn("_row", F.monotonically_increasing_id()))
                hits = reduce(DataFrame.union, [numbered.select("_row", x).join(pairs[x], x).select("_row", KEY) for x in mine]).distinct()
                df = numbered.join(hits, "_row").drop("_row")
            parts[name] = Relation(df.select(*(F.col(f"`{c}`") for c in [*r.vars, KEY])), r.maybe)
            rules[name] = 2
            continue
        if r.df.limit(REPLICATED_ROWS + 1).count() > REPLICATED_ROWS:
            raise ValueError(f"{name} binds no split variable and is too large to go to every batch")
        parts[name] = Relation(domain.select(F.col("c").alias(KEY)).crossJoin(F.broadcast(r.df)), r.maybe)
        rules[name] = 3
    return SplitPlan(parts, rules, domain)


def map_split_two(rels: dict[str, Relation], v1: str, v2: str) -> DataFrame:
    """(c1, c2): the pairs of values that occur together where a sequence binds both, else the product of both domains."""
    for r in rels.values():
        if v1 in r.vars and v2 in r.vars:
            return r.df.select(F.col(v1).alias("c1"), F.col(v2).alias("c2")).dropna().distinct()
    every = list(rels.values())
    return compat.cross(Relation(split_domain(every, v1).withColumnRenamed("c", "c1")), Relation(split_domain(every, v2).withColumnRenamed("c", "c2"))).df


# Lifting: every part of a query that depends on a split sequence carries the batch key.


def lift(node: q.Query, split: set[str]) -> q.Query:
    """The query that evaluates all batches at once and returns the batch key beside its variables."""
    keyed = lambda x: any(isinstance(n, q.VarRef) and n.name in split for n in q.walk(x))
    if not keyed(node):
        return node
    if isinstance(node, q.VarRef):
        return node
    if isinstance(node, (q.Join, q.LeftJoin, q.Union, q.Minus)):
        return replace(node, left=lift(node.left, split), right=lift(node.right, split))
    if isinstance(node, q.Exists):
        return replace(node, body=lift(node.body, split), test=lift(node.test, split))
    if isinstance(node, q.Project):
        return replace(node, body=lift(node.body, split), items=(*node.items, KEY))
    if isinstance(node, q.Group):
        return replace(node, body=lift(node.body, split), keys=(*node.keys, KEY))
    if isinstance(node, (q.Filter, q.Extend, q.Distinct)):
        return replace(node, body=lift(node.body, split))
    raise ValueError(f"{type(node).__name__} cannot be lifted; evaluate by bucket or by value")


@dataclass(frozen=True)
class Reduce:
    """How the results of the batches become one."""

    name: str
    merge: Callable[[DataFrame, DataFrame], DataFrame]

    @staticmethod
    def custom(merge: Callable[[DataFrame, DataFrame], DataFrame]) -> Reduce:
        """``merge(results with the column __c, domain (c))``."""
        return Reduce("custom", merge)


def reduce_union() -> Reduce:
    return Reduce("union", lambda df, domain: df.drop(KEY))


def reduce_distinct() -> Reduce:
    return Reduce("distinct", lambda df, domain: df.drop(KEY).distinct())


def reduce_agg(keys: tuple, name: str, fn: Callable[[Column], Column]) -> Reduce:
    """An aggregate of one variable over the union, by keys or in all."""
    return Reduce("aggregate", lambda df, domain: df.groupBy(*keys).agg(fn(F.col(name)).alias(name)) if keys else df.agg(fn(F.col(name)).alias(name)))


def reduce_sum(name: str, keys: tuple = ()) -> Reduce:
    return reduce_agg(keys, name, lambda c: F.coalesce(F.sum(c), F.lit(0)))


def reduce_intersect(bag: bool = False) -> Reduce:
    """Solutions of every batch; as a bag, as often as in the batch with the fewest."""

    def merge(df: DataFrame, domain: DataFrame) -> DataFrame:
        columns = [c for c in df.columns if c != KEY]
        each = df.groupBy(*columns, KEY).agg(F.count(F.lit(1)).alias("_n"))
        total = domain.agg(F.count(F.lit(1)).alias("_all"))
        found = each.groupBy(*columns).agg(F.count(F.lit(1)).alias("_in"), F.min("_n").alias("_n")).join(F.broadcast(total)).where("_in = _all")
        if bag:
            found = found.withColumn("_k", F.explode(F.sequence(F.lit(1), F.col("_n").cast("int"))))
        return found.select(*columns)

    return Reduce("intersect", merge)


def _merged(reducer: Reduce, df: DataFrame, maybe: frozenset, split: SplitPlan) -> Relation:
    out = reducer.merge(df, split.domain)
    return Relation(out, frozenset(c for c in out.columns if c in maybe or c not in df.columns))


def eval_batches(query: q.Query, split: SplitPlan, env: dict[str, Relation], catalog: Catalog, reducer: Reduce, how: str = "lifted", buckets: int = 8, workers: int = 4, max_values: int = 2_000) -> tuple[Relation, int]:
    """(merged result, number of queries). ``how``: 'lifted', 'bucketed' or 'per_value'."""
    names = set(split.parts)
    if how == "lifted":
        out = compile_query(lift(query, names), {**env, **split.parts}, catalog)
        return _merged(reducer, out.df, out.maybe, split), 1
    if how == "bucketed":
        results, maybe = [], frozenset()
        lifted = lift(query, names)
        for b in range(buckets):
            part = {n: replace(r, df=r.df.where(F.pmod(F.xxhash64(KEY), F.lit(buckets)) == b), rows=None) for n, r in split.parts.items()}
            out = compile_query(lifted, {**env, **part}, catalog)
            maybe |= out.maybe
            results.append(durable(out.df))
        return _merged(reducer, reduce(DataFrame.unionByName, results), maybe, split), buckets
    if how != "per_value":
        raise ValueError(f"unknown way {how!r}")
    values = [r["c"] for r in split.domain.orderBy("c").limit(max_values + 1).collect()]
    if len(values) > max_values:
        raise ValueError(f"more than {max_values} values; evaluate by bucket or lifted")
    snapshots = {n: replace(r, df=durable(r.df)) for n, r in split.parts.items()}

    def one(c) -> DataFrame:
        part = {n: Relation(r.df.where(F.col(KEY) == F.lit(c)).drop(KEY), r.maybe) for n, r in snapshots.items()}
        return durable(compile_query(query, {**env, **part}, catalog).df.withColumn(KEY, F.lit(c)))

    with ThreadPoolExecutor(workers) as pool:
        results = list(pool.map(one, values))
    if not results:
        empty = {n: Relation(r.df.drop(KEY).limit(0), r.maybe) for n, r in split.parts.items()}
        results = [compile_query(query, {**env, **empty}, catalog).df.limit(0).withColumn(KEY, F.lit(None).cast("long"))]
    return Relation.of(reducer.merge(reduce(DataFrame.unionByName, results), split.domain)), len(values)


@dataclass(frozen=True)
class Split:
    """What a statement says about its evaluation in batches."""

    v: str
    inner: tuple = ()
    reads: tuple = ()
    reducer: Reduce = reduce_union()
    how: str = "lifted"
    combine: str = "any"
    buckets: int = 8

    def evaluate(self, query: q.Query, env: dict[str, Relation], catalog: Catalog) -> tuple[Relation, int]:
        names = self.reads or tuple(sorted(q.references(query)))
        plan = map_split({n: env[n] for n in names}, self.v, list(self.inner), catalog, self.combine)
        return eval_batches(query, plan, env, catalog, self.reducer, self.how, self.buckets)


def exactness(query: q.Query, v: str, rules: dict[str, int], certain: set[str] | frozenset = frozenset(), complete: bool = False) -> str:
    """'EXACT' if the union of batches is known to be the full answer, else 'UNKNOWN'.

    ``rules`` has the rule that split each sequence, ``certain`` the sequences that bind ``v`` in every
    solution, and ``complete`` says that the inner queries find every value that can join. Each
    part of a query is then 'keyed', that is, each of its solutions is in one batch only, 'some', a
    selection that is enough to be joined with something keyed, or 'whole', the same in every batch.
    """

    def groups_by_v(node: q.Group) -> bool:
        return any((k if isinstance(k, str) else k[0].name if isinstance(k[0], q.Var) and k[0].name == k[1] else None) == v for k in node.keys)

    def look(node: q.Query) -> tuple[str | None, bool]:
        """(kind, whether ``v`` itself is in scope)."""
        if isinstance(node, q.VarRef):
            rule = rules.get(node.name, 3)
            if rule == 1:
                return ("keyed" if node.name in certain else None), True
            return ("some" if complete else None) if rule == 2 else "whole", False
        if isinstance(node, (q.Pattern, q.Bgp, q.Values, q.Unit)):
            return "whole", False
        if isinstance(node, q.Join):
            (a, x), (b, y) = look(node.left), look(node.right)
            if None in (a, b) or a == b == "keyed" and not (x and y):
                return None, False
            return ("keyed" if "keyed" in (a, b) else "some" if "some" in (a, b) else "whole"), x or y
        if isinstance(node, q.Union):
            (a, x), (b, y) = look(node.left), look(node.right)
            return (a if a == b and a in ("keyed", "whole") else None), x and y
        if isinstance(node, (q.Filter, q.Extend)):
            return look(node.body)
        if isinstance(node, q.Project):
            kind, x = look(node.body)
            kept = v in node.items or any(not isinstance(i, str) and i == (q.Var(v), v) for i in node.items)
            return kind, x and kept
        if isinstance(node, q.Distinct):
            kind, x = look(node.body)
            return (kind if kind == "whole" or kind == "keyed" and x else None), x
        if isinstance(node, q.Group):
            kind, x = look(node.body)
            return (kind if kind == "whole" or kind == "keyed" and x and groups_by_v(node) else None), x
        return None, False

    return "EXACT" if look(query)[0] == "keyed" else "UNKNOWN"


def verdict(query: q.Query, v: str, env: dict[str, Relation], split: SplitPlan, complete: bool = False) -> str:
    """``exactness`` of a split that has been made; sequences that the query reads and the split left alone are whole."""
    certain = {n for n, r in env.items() if v in r.vars and v not in r.maybe}
    return exactness(query, v, split.rules, certain, complete)


# Several split variables: every sequence is split by those that it binds, each batch is a tuple of values.


def lift_tuples(node: q.Query, keys: dict[str, tuple], vs: tuple) -> tuple[q.Query, tuple]:
    """(query that carries one key column for each split variable that its sequences bind, these variables)."""
    column = {v: f"{KEY}_{v}" for v in vs}

    def with_all(x: q.Query, have: tuple, want: tuple) -> q.Query:
        return reduce(lambda a, v: q.Join(a, q.VarRef(f"{KEY}_domain_{v}")), (v for v in want if v not in have), x)

    def go(x: q.Query) -> tuple[q.Query, tuple]:
        if isinstance(x, q.VarRef):
            return x, keys.get(x.name, ())
        if isinstance(x, (q.Join, q.Union)):
            (a, ka), (b, kb) = go(x.left), go(x.right)
            every = tuple(v for v in vs if v in ka or v in kb)
            if isinstance(x, q.Union):  # a side without a key is in every batch of that variable
                a, b = with_all(a, ka, every), with_all(b, kb, every)
            return replace(x, left=a, right=b), every
        if isinstance(x, q.Project):
            body, k = go(x.body)
            return replace(x, body=body, items=(*x.items, *(column[v] for v in k))), k
        if isinstance(x, q.Group):
            body, k = go(x.body)
            return replace(x, body=body, keys=(*x.keys, *(column[v] for v in k))), k
        if isinstance(x, (q.Filter, q.Extend, q.Distinct)):
            body, k = go(x.body)
            return replace(x, body=body), k
        if isinstance(x, (q.Pattern, q.Bgp, q.Values, q.Unit)):
            return x, ()
        raise ValueError(f"{type(x).__name__} cannot be lifted")

    lifted, have = go(node)
    return with_all(lifted, have, vs), vs


def eval_tuples(query: q.Query, env: dict[str, Relation], catalog: Catalog, vs: tuple, reads: tuple) -> Relation:
    """The union of the query's results over all tuples of values of ``vs``, in one query that carries the tuple as keys.

    A sequence keeps, for a tuple, its rows that agree with it on the split variables it binds. A product
    with the values of a variable that a part does not bind needs a small side, which is checked.
    """
    parts, keys = {}, {}
    rels = {n: env[n] for n in reads}
    for name, r in rels.items():
        keys[name] = tuple(v for v in vs if v in r.vars)
        df = r.df
        for v in keys[name]:
            df = df.where(F.col(v).isNotNull()).withColumn(f"{KEY}_{v}", F.col(v))
        parts[name] = Relation(df, r.maybe - set(keys[name]), None if keys[name] else r.rows)
    domains = {f"{KEY}_domain_{v}": Relation(split_domain(list(rels.values()), v).withColumnRenamed("c", f"{KEY}_{v}")) for v in vs}
    lifted, _ = lift_tuples(query, keys, vs)
    out = compile_query(lifted, {**env, **parts, **domains}, catalog)
    return Relation(out.df.drop(*(f"{KEY}_{v}" for v in vs)), out.maybe)


def batch_stats(split: SplitPlan) -> DataFrame:
    """(c, rows): rows shipped for each batch, over all sequences."""
    counts = [r.df.groupBy(F.col(KEY).alias("c")).agg(F.count(F.lit(1)).alias("n")) for r in split.parts.values()]
    both = reduce(DataFrame.union, counts)
    return split.domain.join(both, "c", "left").groupBy("c").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("rows"))
