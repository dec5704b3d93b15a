"""Connected components by alternating large-star and small-star contraction.

Every round rewires edges towards the smallest neighbour; the rounds needed grow with the
logarithm of the number of nodes, not with the diameter. A hub's neighbours are never
gathered: the smallest neighbour is a combinable minimum that is joined back to the edges.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.materialize import durable

PART_EDGES = 1_000_000


def _forest(edges: DataFrame, parts: int) -> DataFrame:
    """Each of ``parts`` parts of the edges (hi, lo) as stars around its components' least nodes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        up: dict[int, int] = {}

        def find(x: int) -> int:
            top = x
            while (above := up.get(top, top)) != top:
                top = above
            while (above := up.get(x, x)) != top:
                up[x], x = top, above
            return top

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                a, b = find(a), find(b)
                if a != b:
                    up[max(a, b)] = min(a, b)
        nodes = np.fromiter(up, dtype=np.int64, count=len(up))
        tops = np.fromiter(map(find, up), dtype=np.int64, count=len(up))
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(tops)], names=["hi", "lo"])

    return edges.coalesce(parts).mapInArrow(run, "hi long, lo long")


def _towards_least(edges: DataFrame, small: bool) -> DataFrame:
    """One star step on edges (hi, lo) with hi > lo."""
    if small:
        near = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v"))
    else:
        near = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(edges.select("lo", "hi"))
    least = near.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    moved = near.join(least, "u")
    if small:
        moved = moved.select(F.col("v").alias("hi"), F.col("m").alias("lo")).union(least.select(F.col("u"), F.col("m")))
    else:
        moved = moved.where(F.col("v") > F.col("u")).select(F.col("v").alias("hi"), F.col("m").alias("lo"))
    return moved.where(F.col("hi") != F.col("lo")).distinct()


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
    return tuple(row)


def contract(edges: DataFrame, max_rounds: int = 64, local: bool = True, part_edges: int = PART_EDGES) -> tuple[DataFrame, int]:
    """((node, component) for every node that has an edge to a smaller one, rounds).

    ``edges`` has columns src and dst, of any direction, repeated or looped; ``component`` is
    the smallest node of the component, which itself is not listed. With ``local`` the edges
    are first reduced to forests in parts of about ``part_edges``; a single part is the answer.
    """
    pairs = edges.where(F.col("src") != F.col("dst")).select(F.greatest("src", "dst").alias("hi"), F.least("src", "dst").alias("lo"))
    current = durable(pairs if local else pairs.distinct())
    if local:
        parts = current.count() // part_edges + 1
        current = durable(_forest(current, parts))
        if parts == 1:
            return current.select(F.col("hi").alias("node"), F.col("lo").alias("component")), 1
    before, rounds = _state(current), 0
    while before[0]:
        rounds += 1
        if rounds > max_rounds:
            raise RuntimeError(f"no fixpoint after {max_rounds} rounds")
        current = durable(_towards_least(_towards_least(current, small=False), small=True))
        after = _state(current)
        if after == before:
            break
        before = after
    return current.select(F.col("hi").alias("node"), F.col("lo").alias("component")), rounds
