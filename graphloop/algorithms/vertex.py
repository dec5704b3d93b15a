"""Vertex programs compiled to procedures, and the traversals built on them.

A program sends a value along every edge whose source changed in the last round, merges what
arrives at a node with a combinable aggregate, and keeps what improves the node's state.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import Procedure, Until
from graphloop.plans.runtime import RunResult, run
from graphloop.relation import Relation


def vertex_program(edges: DataFrame, state: DataFrame, message: Column, merge: Callable = F.min, better: Callable | None = None, max_rounds: int = 10_000) -> RunResult:
    """(node, value) once nothing improves.

    ``state`` has (node, value) of the nodes that are set at the start; ``message`` is an
    expression over value, src, dst and the columns of ``edges``; ``better(new, old)`` decides
    about a node that has a value, and every node without one takes what arrives. Only nodes
    that changed send. The state is a log of what was found, by round, in a bounded number of
    snapshots that lie by node: a round writes what it changes, and deals out what is sent.
    """
    better = better or (lambda new, old: new < old)

    def arrive(env) -> Relation:
        sent = env["changed"].df.withColumnRenamed("node", "src").join(env["edges"].df, "src")
        found = sent.select(F.col("dst").alias("node"), message.alias("value"), (F.col("_round") + 1).alias("_round"))
        found = found.groupBy("node").agg(merge("value").alias("value"), F.max("_round").alias("_round"))
        old = env["state"].df.groupBy("node").agg(F.max_by("value", "_round").alias("old"))
        fresh = found.join(old, "node", "left").where(F.col("old").isNull() | better(F.col("value"), F.col("old")))
        return Relation(fresh.select("node", "value", "_round"))

    proc = Procedure().let("edges", lambda env: Relation(edges))
    proc.let("state", lambda env: Relation(state.select("node", "value", F.lit(0).alias("_round"))))
    proc.let("changed", q.VarRef("state"))
    body = Procedure().let("changed", arrive, reads=("changed", "edges", "state")).let("state", q.Union(q.VarRef("state"), q.VarRef("changed")))
    proc.loop(body, Until(lambda env, before: env["changed"].rows == 0, ("changed",)), max_rounds, keys=(("edges", "src"), ("state", "node")))
    found = run(proc.ret("state"), Catalog(edges.sparkSession))
    last = found.df.groupBy("node").agg(F.max_by("value", "_round").alias("value"))
    return replace(found, relation=Relation(last))


def _start(edges: DataFrame, source: int, value) -> DataFrame:
    kind = dict(edges.dtypes)["src"]
    return edges.sparkSession.range(1).select(F.lit(source).cast(kind).alias("node"), F.lit(value).alias("value"))


def both_ways(edges: DataFrame) -> DataFrame:
    """Every edge in both directions, once."""
    flipped = edges.withColumns({"src": F.col("dst"), "dst": F.col("src")})
    return edges.unionByName(flipped).distinct()


def bfs(edges: DataFrame, source: int, directed: bool = True, unreachable: str = "omit") -> DataFrame:
    """(node, level): hops from the source. Nodes that are not reached are left out, or have null, or the largest long.

    A frontier traversal: levels only ever appear, so a round joins the last level with the
    edges and drops what is known.
    """
    edges = (edges.select("src", "dst") if directed else both_ways(edges.select("src", "dst"))).distinct()
    catalog = Catalog(edges.sparkSession)

    def arrive(env) -> Relation:
        reached = env["last"].df.select(F.col("node").alias("src"), F.col("level")).join(env["edges"].df, "src")
        found = reached.groupBy(F.col("dst").alias("node")).agg((F.min("level") + 1).alias("level"))
        return Relation(found.join(env["levels"].df.select("node"), "node", "left_anti"))

    start = _start(edges, source, 0).select("node", F.col("value").cast("long").alias("level"))
    proc = Procedure().let("edges", lambda env: Relation(edges)).let("levels", lambda env: Relation(start)).let("last", q.VarRef("levels"))
    body = Procedure().let("last", arrive, reads=("last", "edges", "levels")).let("levels", q.Union(q.VarRef("levels"), q.VarRef("last")))
    done = Until(lambda env, before: env["last"].rows == 0, ("last",))
    levels = run(proc.loop(body, done, keys=(("edges", "src"), ("levels", "node"))).ret("levels"), catalog).df
    if unreachable == "omit":
        return levels
    nodes = edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct()
    far = F.lit(None).cast("long") if unreachable == "null" else F.lit(2**63 - 1)
    return nodes.join(levels, "node", "left").withColumn("level", F.coalesce("level", far))


def sssp(edges: DataFrame, source: int, weight: str | None = None) -> DataFrame:
    """(node, dist) over non-negative weights, hops if none are named; nodes that are not reached are left out."""
    cost = F.col(weight) if weight else F.lit(1.0)
    edges = edges.select("src", "dst", cost.cast("double").alias("_cost"))
    found = vertex_program(edges, _start(edges, source, 0.0), F.col("value") + F.col("_cost"))
    return found.df.select("node", F.col("value").alias("dist"))


def busiest_source(edges: DataFrame) -> int:
    """The node with the largest out-degree, ties to the smallest."""
    return edges.groupBy("src").count().orderBy(F.col("count").desc(), "src").first()["src"]
