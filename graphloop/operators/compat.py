"""Joins of solution sequences in which an unbound variable is compatible with anything.

Where all shared variables are certain these are Spark's joins. Otherwise the solutions are
split by which shared variables they leave unbound, and each pair of classes is an equi-join
on the variables bound in both: there is no nested loop, whatever the sizes.
"""

from __future__ import annotations

from itertools import chain, combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.materialize import durable
from graphloop.relation import Relation, TooLarge

CROSS_ROWS = 1_000_000


class CrossJoinTooLarge(TooLarge):
    """Neither side of a product is small."""


def _subsets(names) -> list[tuple[str, ...]]:
    names = sorted(names)
    return list(chain.from_iterable(combinations(names, k) for k in range(len(names) + 1)))


def _quoted(name: str) -> Column:
    return F.col(f"`{name}`")


def _where_bound(df: DataFrame, maybe: list[str], unbound: tuple[str, ...]) -> DataFrame:
    for name in maybe:
        df = df.where(_quoted(name).isNull() if name in unbound else _quoted(name).isNotNull())
    return df


def union(a: Relation, b: Relation) -> Relation:
    """Bag union; variables of one side only are unbound in the other."""
    if not a.vars and not b.vars:
        return Relation(a.df.union(b.df))
    missing = set(a.vars) ^ set(b.vars)
    return Relation(a.df.unionByName(b.df, allowMissingColumns=True), a.maybe | b.maybe | frozenset(missing))


def cross(a: Relation, b: Relation) -> Relation:
    """Product for sequences without shared variables; one side must have at most ``CROSS_ROWS`` rows, which is checked."""
    for small, large in ((b, a), (a, b)):
        n = small.rows if small.rows is not None else small.df.limit(CROSS_ROWS + 1).count()
        if n <= CROSS_ROWS:
            out = large.df.crossJoin(F.broadcast(small.df)).select(*(_quoted(c) for c in [*a.vars, *b.vars]))
            known = small.rows is not None and large.rows is not None
            return Relation(out, a.maybe | b.maybe, small.rows * large.rows if known else None)
    raise CrossJoinTooLarge(f"both sides of a product have more than {CROSS_ROWS} rows")


def _classes(a: Relation, b: Relation, shared: list[str]):
    ma, mb = sorted(a.maybe & set(shared)), sorted(b.maybe & set(shared))
    for ua in _subsets(ma):
        for ub in _subsets(mb):
            yield _where_bound(a.df, ma, ua), _where_bound(b.df, mb, ub), [c for c in shared if c not in ua and c not in ub]


def join(a: Relation, b: Relation, hint: str | None = None) -> Relation:
    """Compatibility join."""
    shared = [c for c in a.vars if c in b.vars]
    if not shared:
        return cross(a, b)
    right = b.df.hint(hint) if hint else b.df
    if not (a.maybe | b.maybe) & set(shared):
        return Relation(a.df.join(right, shared).select(*(_quoted(c) for c in dict.fromkeys([*a.vars, *b.vars]))), a.maybe | b.maybe)
    names = list(dict.fromkeys([*a.vars, *b.vars]))
    out = None
    for left, right, keys in _classes(a, b, shared):
        renamed = right.select(*(_quoted(c).alias(f"_r_{c}") for c in b.vars))
        condition = [_quoted(c) == F.col(f"`_r_{c}`") for c in keys]
        if condition:
            both = left.join(renamed, condition)
        else:
            both = cross(Relation(left), Relation(renamed)).df
        merged = both.select(*(F.coalesce(_quoted(c), F.col(f"`_r_{c}`")).alias(c) if c in shared else _quoted(c) if c in a.vars else F.col(f"`_r_{c}`").alias(c) for c in names))
        out = merged if out is None else out.unionByName(merged)
    maybe = (a.maybe & b.maybe & frozenset(shared)) | ((a.maybe | b.maybe) - frozenset(shared))
    return Relation(out, maybe)


def left_join(a: Relation, b: Relation, condition=None) -> Relation:
    """OPTIONAL: every left solution, extended where a compatible right one meets ``condition``.

    ``condition`` is a function from the joined relation to a boolean column.
    """
    shared = [c for c in a.vars if c in b.vars]
    extra = [c for c in b.vars if c not in a.vars]
    if shared and condition is None and not (a.maybe | b.maybe) & set(shared):
        out = a.df.join(b.df, shared, "left").select(*(_quoted(c) for c in [*a.vars, *extra]))
        return Relation(out, a.maybe | b.maybe | frozenset(extra))
    numbered = Relation(a.df.withColumn("_row", F.monotonically_increasing_id()), a.maybe)
    numbered = Relation(durable(numbered.df), a.maybe)
    both = join(numbered, b)
    if condition is not None:
        both = Relation(both.df.where(F.coalesce(condition(both), F.lit(False))), both.maybe)
    rest = numbered.df.join(both.df.select("_row").distinct(), "_row", "left_anti")
    out = both.df.unionByName(rest, allowMissingColumns=True).drop("_row")
    return Relation(out.select(*(_quoted(c) for c in [*a.vars, *extra])), a.maybe | b.maybe | frozenset(extra))


def minus(a: Relation, b: Relation) -> Relation:
    """Left solutions without a compatible right one that shares a bound variable with them."""
    shared = [c for c in a.vars if c in b.vars]
    if not shared:
        return a
    if not (a.maybe | b.maybe) & set(shared):
        return Relation(a.df.join(b.df.select(*shared), shared, "left_anti").select(*(_quoted(c) for c in a.vars)), a.maybe)
    ma, mb = sorted(a.maybe & set(shared)), sorted(b.maybe & set(shared))
    out = None
    for ua in _subsets(ma):
        left = _where_bound(a.df, ma, ua)
        for ub in _subsets(mb):
            keys = [c for c in shared if c not in ua and c not in ub]
            if keys:
                right = _where_bound(b.df, mb, ub).select(*(_quoted(c) for c in keys))
                left = left.join(right, keys, "left_anti").select(*(_quoted(c) for c in a.vars))
        out = left if out is None else out.unionByName(left)
    return Relation(out, a.maybe)


def exists(a: Relation, b: Relation, negated: bool) -> Relation:
    """Left solutions with (or without) a compatible right one; unlike MINUS, with no shared variable any row counts."""
    shared = [c for c in a.vars if c in b.vars]
    if not shared:
        keep = b.df.isEmpty() == negated
        return a if keep else Relation(a.df.limit(0), a.maybe)
    if not (a.maybe | b.maybe) & set(shared):
        kind = "left_anti" if negated else "left_semi"
        return Relation(a.df.join(b.df.select(*shared), shared, kind).select(*(_quoted(c) for c in a.vars)), a.maybe)
    numbered = durable(a.df.withColumn("_row", F.monotonically_increasing_id()))
    hits = join(Relation(numbered, a.maybe), b).df.select("_row").distinct()
    kind = "left_anti" if negated else "left_semi"
    return Relation(numbered.join(hits, "_row", kind).drop("_row"), a.maybe)
