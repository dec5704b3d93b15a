"""Reachability that avoids nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame

from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import Fixpoint, Procedure
from graphloop.plans.rewrite import optimise
from graphloop.plans.runtime import RunResult, run


def reach_procedure(source: int, direction: str = "out", include_source: bool = False, check: str = "fingerprint") -> Procedure:
    """Allowed neighbours of the source, then of what is known, until nothing is new.

    The answer binds ``node``. Reads the predicates ``step`` and ``blocked`` (a node twice). The source is not part of
    the answer unless it can be come back to, or ``include_source``.
    """
    ahead, back = q.Pattern("?from", "step", "?node"), q.Pattern("?node", "step", "?from")
    edge = {"out": ahead, "in": back, "both": q.Union(ahead, back)}[direction]
    passable = q.Minus(edge, q.Project(q.Pattern("?node", "blocked", "?why"), ("node",)))
    first = q.Project(q.Filter(q.VarRef("passable"), q.call("=", "?from", source)), ("node",))
    if include_source:
        first = q.Union(first, q.Values(("node",), ((source,),)))
    onward = q.Join(q.Project(q.VarRef("known"), ((q.Var("node"), "from"),)), q.VarRef("passable"))
    body = Procedure().let("found", q.Project(onward, ("node",))).let("known", q.Distinct(q.Union(q.VarRef("found"), q.VarRef("known"))))
    return Procedure().let("passable", passable, lazy=True).let("known", q.Distinct(first)).loop(body, Fixpoint("known", check)).ret("known")


def graph_catalog(edges: DataFrame, blocked: DataFrame | None = None) -> Catalog:
    """Edges (src, dst) as ``step`` and nodes (node) as ``blocked``."""
    spark = edges.sparkSession
    catalog = Catalog(spark).add("step", edges, "src", "dst")
    blocked = spark.createDataFrame([], "node long") if blocked is None else blocked
    return catalog.add("blocked", blocked.selectExpr("node AS s", "node AS o"))


def reach_avoiding(edges: DataFrame, source: int, blocked: DataFrame | None = None, include_source: bool = False, direction: str = "out", rewrite: bool = True, mode: str = "plan", check: str = "fingerprint") -> RunResult:
    """Nodes reachable from ``source`` through nodes that are not blocked; with ``rewrite`` each round extends new nodes only."""
    proc = reach_procedure(source, direction, include_source, check)
    return run(optimise(proc) if rewrite else proc, graph_catalog(edges, blocked), mode=mode)
