"""Message passing layers over node vectors, with readouts, and local procedures."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.materialize import durable
from graphloop.plans import query as q
from graphloop.plans.batches import Split, reduce_union
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import Procedure, Times

ACTIVATIONS: dict[str, Callable] = {"none": lambda x: x, "relu": lambda x: F.greatest(x, F.lit(0.0)), "tanh": F.tanh}


@dataclass(frozen=True)
class Layer:
    """new = act(own weight * own + neighbour weight * aggregate + bias); scalars act on every coordinate, matrices mix them.

    ``own`` and ``near`` are numbers or square matrices (lists of rows).
    """

    agg: str = "sum"
    own: float | list = 1.0
    near: float | list = 1.0
    bias: float | list = 0.0
    act: str = "none"


def explode_vectors(features: DataFrame) -> DataFrame:
    """(node, pos, value) from (node, x)."""
    return features.select("node", F.posexplode("x").alias("pos", "value")).withColumn("value", F.col("value").cast("double"))


def _mixed(df: DataFrame, weight, name: str) -> DataFrame:
    """(node, pos, name) of a weight times (node, pos, value)."""
    if isinstance(weight, (int, float)):
        return df.select("node", "pos", (F.col("value") * F.lit(float(weight))).alias(name))
    rows = [(i, j, float(w)) for i, row in enumerate(weight) for j, w in enumerate(row) if w]
    matrix = df.sparkSession.createDataFrame(rows, "out int, pos int, w double")
    joined = df.join(F.broadcast(matrix), "pos")
    return joined.groupBy("node", F.col("out").alias("pos")).agg(F.sum(F.col("value") * F.col("w")).alias(name))


def gnn(edges: DataFrame, features: DataFrame, layers: list[Layer], readout: str | None = None, undirected: bool = False, edge_update: Callable | None = None) -> DataFrame:
    """(node, pos, value) after the layers, or (pos, value) of a readout: sum, mean or max.

    A node aggregates over the targets of its edges. Nodes without neighbours aggregate to 0.
    ``edge_update(old, source value, target value)`` keeps a vector on each edge, which starts
    at 0 and is added to what a neighbour sends.
    """
    near = edges.select("src", "dst")
    if undirected:
        near = near.union(edges.select("dst", "src")).distinct()
    near = durable(near)
    state = durable(explode_vectors(features))
    carried = None
    for layer in layers:
        sent = near.join(state.select(F.col("node").alias("dst"), "pos", "value"), "dst")
        if edge_update is not None:
            both = sent.join(state.select(F.col("node").alias("src"), "pos", F.col("value").alias("own")), ["src", "pos"])
            both = both.withColumn("kept", F.lit(0.0)) if carried is None else both.join(carried, ["src", "dst", "pos"])
            carried = durable(both.select("src", "dst", "pos", edge_update(F.col("kept"), F.col("own"), F.col("value")).alias("kept")))
            sent = sent.join(carried, ["src", "dst", "pos"]).withColumn("value", F.col("value") + F.col("kept"))
        fn = {"sum": F.sum, "mean": F.avg, "max": F.max}[layer.agg]
        heard = sent.groupBy(F.col("src").alias("node"), "pos").agg(fn("value").alias("value"))
        own, around = _mixed(state, layer.own, "a"), _mixed(heard, layer.near, "b")
        bias = F.lit(layer.bias) if isinstance(layer.bias, (int, float)) else F.get(F.array(*map(F.lit, layer.bias)), F.col("pos"))
        total = F.coalesce("a", F.lit(0.0)) + F.coalesce("b", F.lit(0.0)) + bias
        state = durable(state.select("node", "pos").join(own, ["node", "pos"], "left").join(around, ["node", "pos"], "left").select("node", "pos", ACTIVATIONS[layer.act](total).alias("value")))
    if readout is None:
        return state
    fn = {"sum": F.sum, "mean": F.avg, "max": F.max}[readout]
    return state.groupBy("pos").agg(fn("value").alias("value"))


def edge_states(edges: DataFrame, features: DataFrame, layers: list[Layer], edge_update: Callable) -> DataFrame:
    """(src, dst, pos, value): the vectors that edges hold after the layers."""
    state, carried = durable(explode_vectors(features)), None
    near = durable(edges.select("src", "dst"))
    for layer in layers:
        both = near.join(state.select(F.col("node").alias("dst"), "pos", "value"), "dst").join(state.select(F.col("node").alias("src"), "pos", F.col("value").alias("own")), ["src", "pos"])
        both = both.withColumn("kept", F.lit(0.0)) if carried is None else both.join(carried, ["src", "dst", "pos"])
        carried = durable(both.select("src", "dst", "pos", edge_update(F.col("kept"), F.col("own"), F.col("value")).alias("kept")))
    return carried.withColumnRenamed("kept", "value")


def local_wl_procedure(predicates: list[str], rounds: int) -> Procedure:
    """Colour refinement inside the local fragment: labels are texts that list what they stand for.

    One statement for each neighbourhood, a vector from the label predicate, and a loop that is split by ?v alone.
    """
    proc = Procedure()
    for k, p in enumerate(predicates):
        proc.let(f"near_{k}", q.Project(q.Pattern("?v", p, f"?v{k}"), ("v", f"v{k}")))
    proc.let("vector", q.Project(q.Pattern("?v", "label", "?lab"), ("v", "lab")))
    body = Procedure()
    gathered: list[str] = []
    for k in range(len(predicates)):
        heard = q.Join(q.VarRef(f"near_{k}"), q.Project(q.VarRef("vector"), ((q.Var("v"), f"v{k}"), (q.Var("lab"), f"lab{k}"))))
        body.let(f"heard_{k}", q.Group(heard, ("v",), ((f"list{k}", q.Agg("group_concat", q.Var(f"lab{k}"))),)), split=Split("v", (), (f"near_{k}",), reduce_union()))
        gathered.append(f"heard_{k}")
    joined: q.Query = q.VarRef("vector")
    for name in gathered:
        joined = q.LeftJoin(joined, q.VarRef(name))
    lists = [q.call("coalesce", f"?list{k}", "?lab") for k in range(len(predicates))]
    label = q.call("md5", q.call("concat", "?lab", *lists))
    body.let("vector", q.Project(joined, ("v", (label, "lab"))), split=Split("v", (), ("vector", *gathered), reduce_union()))
    return proc.loop(body, Times(rounds)).ret("vector")


def bound_violations(result: DataFrame, classes: DataFrame) -> DataFrame:
    """Classes (node, class) whose nodes a result (v, lab) labels differently."""
    return classes.join(result.withColumnRenamed("v", "node"), "node").groupBy("class").agg(F.count_distinct("lab").alias("n")).where("n > 1")


def label_catalog(spark, edges: DataFrame, labels: DataFrame) -> Catalog:
    """Edges as the predicate ``near``, node labels as ``label`` (text)."""
    return Catalog(spark).add("near", edges, "src", "dst").add("label", labels.select("node", F.col("label").cast("string").alias("label")), "node", "label")
