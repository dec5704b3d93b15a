"""Measures of tasks and graphs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloop.algorithms.pagerank import node_set
from graphloop.plans.runtime import InlineLimit, TimeLimit, time_limit
from graphloop.relation import TooLarge


def graph_size(edges: DataFrame) -> DataFrame:
    """(nodes, edges) of distinct edges; ends may have different types."""
    pairs = edges.select("src", "dst").distinct()
    ends = pairs.select(F.col("src").cast("string").alias("x")).union(pairs.select(F.col("dst").cast("string"))) if dict(edges.dtypes)["src"] != dict(edges.dtypes)["dst"] else node_set(pairs).toDF("x")
    nodes = ends.distinct().agg(F.count(F.lit(1)).alias("nodes"))
    return nodes.crossJoin(pairs.agg(F.count(F.lit(1)).alias("edges")))


def measure(task: Callable[[], DataFrame], timeout_s: float = 600) -> dict:
    """Seconds, rows and status (ok, timeout, memory, skipped, error) of a task with its subgraph query.

    Jobs that run longer than ``timeout_s`` are cancelled. A task is skipped where it would need a
    product or a query text that is too large.
    """
    began = time.time()
    out = {"seconds": None, "rows": None, "status": "ok"}
    try:
        with time_limit(SparkSession.getActiveSession(), timeout_s):
            out["rows"] = task().count()
    except TimeLimit:
        out["status"] = "timeout"
    except MemoryError:
        out["status"] = "memory"
    except (TooLarge, InlineLimit):
        out["status"] = "skipped"
    except Exception as problem:  # noqa: BLE001  the report must go on
        out["status"] = "memory" if "OutOfMemory" in str(problem) else "error"
    out["seconds"] = round(time.time() - began, 3)
    return out


def rank_error(rank: DataFrame, expected: dict) -> float:
    """Largest difference from reference ranks."""
    other = rank.sparkSession.createDataFrame(list(expected.items()), "node long, expected double")
    return rank.join(other, "node", "full").agg(F.max(F.abs(F.coalesce("rank", F.lit(9.0)) - F.coalesce("expected", F.lit(-9.0))))).first()[0] or 0.0
