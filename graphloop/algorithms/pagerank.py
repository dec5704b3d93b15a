"""PageRank by its procedure, stopping conditions for it, and the p-index of authors."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.algorithms import procedures
from graphloop.algorithms.reach import graph_catalog
from graphloop.plans.parser import parse_procedure
from graphloop.plans.procedure import Loop, Procedure, Until
from graphloop.plans.rewrite import optimise
from graphloop.plans.runtime import RunResult, run
from graphloop.relation import Relation


def node_set(edges: DataFrame) -> DataFrame:
    """(node) of both ends of the edges."""
    return edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct()


def out_degree(edges: DataFrame) -> DataFrame:
    """(node, degree) where it is at least 1; parallel edges count."""
    return edges.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("degree"))


def pagerank_procedure(damping: float = 0.85, until=None, with_nodes: bool = False, batched: str | None = None) -> Procedure:
    """The procedure over the predicate ``step``; parallel edges count.

    ``until`` replaces its ten rounds, ``with_nodes`` takes the nodes from the variable ``place``,
    and ``batched`` says how its sending statement is split ('bucketed', 'lifted' or 'per_value').
    """
    text = procedures.LINK.replace("DISTINCT ", "") + ("" if with_nodes else procedures.ENDS) + procedures.pagerank_text(damping)
    proc = parse_procedure(text)
    if until is not None:
        proc = Procedure([replace(s, until=until) if isinstance(s, Loop) else s for s in proc.statements])
    return procedures.split_sends(proc, "pr", batched) if batched else proc


def pagerank(edges: DataFrame, nodes: DataFrame | None = None, damping: float = 0.85, until=None, hoist: bool = True, spread: str | None = None) -> RunResult:
    """(node, rank); ranks sum to 1 after every round. No nodes give no rows.

    With ``hoist`` the procedure is rewritten before it runs; ``spread`` evaluates what flows along
    edges in batches by the node that sends.
    """
    proc = pagerank_procedure(damping, until, nodes is not None, spread)
    env = {} if nodes is None else {"place": Relation(nodes.select("node"))}
    mode = "batched" if spread else "plan"
    found = run(optimise(proc) if hoist and not spread else proc, graph_catalog(edges), mode=mode, strict=nodes is None, env=env)
    return replace(found, relation=Relation(found.df.select("node", F.col("rank").cast("double").alias("rank"))))


def residual(env, before, norm: str = "l1") -> float:
    """How far ranks moved in a round: l1, l2 or linf."""
    a, b = before["held"].df.select("node", F.col("rank").alias("old")), env["held"].df.select("node", "rank")
    d = F.abs(F.col("rank") - F.col("old"))
    size = {"l1": F.sum(d), "l2": F.sqrt(F.sum(d * d)), "linf": F.max(d)}[norm]
    return a.join(b, "node").agg(size).first()[0] or 0.0


def correlation(env, before) -> float | None:
    """Of the ranks before and after a round."""
    a = before["held"].df.select("node", F.col("rank").cast("double").alias("x"))
    both = a.join(env["held"].df.select("node", F.col("rank").cast("double").alias("y")), "node")
    spread = F.stddev_pop("x") * F.stddev_pop("y")
    return both.agg(F.when(spread > 1e-24, F.try_divide(F.covar_pop("x", "y"), spread))).first()[0]


def residual_below(eps: float, norm: str = "l1", seen: list | None = None) -> Until:
    """Stops when ranks move by less than ``eps`` in a round; ``seen`` collects how far they moved."""

    def test(env, before) -> bool:
        moved = residual(env, before, norm)
        if seen is not None:
            seen.append(moved)
        return moved < eps

    return Until(test, ("held",))


def correlation_above(rho: float, seen: list | None = None) -> Until:
    """Stops when the ranks of two rounds correlate by more than ``rho``; equal first ranks have no correlation."""

    def test(env, before) -> bool:
        found = correlation(env, before)
        if seen is not None:
            seen.append(found)
        return found is not None and found > rho

    return Until(test, ("held",))


def p_index(rank: DataFrame, authorship: DataFrame, top: int | None = 1, names: DataFrame | None = None) -> DataFrame:
    """(author, [name,] p_index): the sum of the ranks of an author's nodes; the ``top`` largest, ties to the smaller author.

    ``authorship`` has (node, author), ``names`` (author, name); names are looked up for the winners only.
    """
    sums = rank.join(authorship, "node").groupBy("author").agg(F.sum("rank").alias("p_index"))
    if top is not None:
        sums = sums.orderBy(F.col("p_index").desc(), "author").limit(top)
    return sums if names is None else sums.join(names, "author").select("author", "name", "p_index")
