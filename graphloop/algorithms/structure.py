"""Components, clustering, communities and colour classes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphloop.algorithms.components import contract
from graphloop.algorithms.pagerank import node_set
from graphloop.algorithms.vertex import both_ways, vertex_program
from graphloop.materialize import durable
from graphloop.plans.catalog import Catalog
from graphloop.plans.procedure import Procedure, Times, Until
from graphloop.plans.runtime import run
from graphloop.relation import Relation


def wcc(edges: DataFrame, method: str = "star", local: bool = True) -> DataFrame:
    """(node, component): the smallest node of the weakly connected component.

    'star' contracts in a number of rounds that grows with the logarithm of the nodes;
    'minlabel' spreads the smallest label along edges, one hop a round.
    """
    edges = edges.select("src", "dst")
    nodes = node_set(edges)
    if method == "minlabel":
        found = vertex_program(both_ways(edges), nodes.select("node", F.col("node").alias("value")), F.col("value"))
        return found.df.select("node", F.col("value").alias("component"))
    if method != "star":
        raise ValueError(f"unknown method {method!r}")
    roots, _ = contract(edges, local=local)
    return nodes.join(roots, "node", "left").select("node", F.coalesce("component", "node").alias("component"))


def _oriented(edges: DataFrame) -> DataFrame:
    """Undirected edges (a, b) once, from the node of smaller degree to the larger; loops go."""
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct()
    degree = pairs.select(F.explode(F.array("x", "y")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("d"))
    with_x = pairs.join(degree.select(F.col("node").alias("x"), F.col("d").alias("dx")), "x")
    both = with_x.join(degree.select(F.col("node").alias("y"), F.col("d").alias("dy")), "y")
    first = (F.col("dx") < F.col("dy")) | ((F.col("dx") == F.col("dy")) & (F.col("x") < F.col("y")))
    return both.select(F.when(first, F.col("x")).otherwise(F.col("y")).alias("a"), F.when(first, F.col("y")).otherwise(F.col("x")).alias("b"))


def triangles(edges: DataFrame) -> DataFrame:
    """(a, b, c) of each undirected triangle once.

    Wedges start at the node of smallest degree, so a hub starts none of its own, and their
    number is bounded by the edges to the power 1.5.
    """
    up = durable(_oriented(edges))
    ab = up.select("a", "b")
    wedge = ab.join(ab.withColumnRenamed("b", "c"), "a").where(F.col("b") < F.col("c"))
    closing = up.select(F.least("a", "b").alias("b"), F.greatest("a", "b").alias("c"))
    return wedge.join(closing, ["b", "c"]).select("a", "b", "c")


def lcc(edges: DataFrame, directed: bool = True) -> DataFrame:
    """(node, lcc): the share of ordered pairs of neighbours that an edge joins; 0 below two neighbours.

    Each undirected triangle gives each of its corners the directed edges of the opposite side.
    """
    pairs = edges.where("src <> dst").select("src", "dst").distinct()
    if not directed:
        pairs = both_ways(pairs)
    pairs = durable(pairs)
    sides = pairs.groupBy(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).agg(F.count(F.lit(1)).alias("m"))
    degree = sides.select(F.explode(F.array("x", "y")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n"))
    t = triangles(pairs)
    corners = F.explode(
        F.array(*(F.struct(F.col(v).alias("node"), F.least(p, q).alias("x"), F.greatest(p, q).alias("y")) for v, p, q in (("a", "b", "c"), ("b", "a", "c"), ("c", "a", "b"))))
    )
    opposite = t.select(corners.alias("k")).select("k.node", "k.x", "k.y").join(sides, ["x", "y"])
    inside = opposite.groupBy("node").agg(F.sum("m").alias("inside"))
    nodes = node_set(edges.select("src", "dst"))
    value = F.when(F.col("n") > 1, F.coalesce("inside", F.lit(0)) / (F.col("n") * (F.col("n") - 1))).otherwise(0.0)
    return nodes.join(degree, "node", "left").join(inside, "node", "left").select("node", value.cast("double").alias("lcc"))


def cdlp(edges: DataFrame, rounds: int = 10, labels: DataFrame | None = None, directed: bool = True) -> DataFrame:
    """(node, label) after synchronous rounds: the most frequent label over in- and out-edges, ties to the smallest.

    Labels start as ``labels`` (node, label), or as the nodes themselves. Counts are combined
    before they move; no list of labels is ever built. A pair with edges both ways counts twice if ``directed``.
    """
    pairs = edges.select("src", "dst").distinct()
    flipped = pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    near = pairs.union(flipped) if directed else pairs.union(flipped).distinct()
    nodes = node_set(pairs)
    start = nodes.select("node", F.col("node").alias("label")) if labels is None else nodes.join(labels, "node").select("node", "label")

    def adopt(env) -> Relation:
        heard = env["near"].df.join(env["labels"].df.withColumnRenamed("node", "src"), "src")
        counts = heard.groupBy(F.col("dst").alias("node"), "label").agg(F.count(F.lit(1)).alias("n"))
        best = counts.groupBy("node").agg(F.max(F.struct("n", (-F.col("label")).alias("l"))).alias("best"))
        heard_by = env["labels"].df.join(best, "node", "left")
        return Relation(heard_by.select("node", F.coalesce(-F.col("best.l"), F.col("label")).alias("label")))

    proc = Procedure().let("near", lambda env: Relation(near)).let("labels", lambda env: Relation(start))
    body = Procedure().let("labels", adopt, reads=("near", "labels"))
    return run(proc.loop(body, Times(rounds), keys=(("near", "src"),)).ret("labels"), Catalog(edges.sparkSession)).df


def weisfeiler_lehman(edges: DataFrame, labels: DataFrame, rounds: int | None = None, undirected: bool = True):
    """((node, class), classes after each round): colour refinement from ``labels`` (node, label).

    A class is named by its smallest node, so partitions can be compared. Without ``rounds``
    it runs until the number of classes stops growing. A node's signature is a hash of its
    class and the sorted counts of classes around it; 128 bits, so equal means alike.
    """
    near = both_ways(edges.select("src", "dst")) if undirected else edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")).distinct()
    sizes: list[int] = []

    def named(df: DataFrame, *key: str) -> DataFrame:
        least = df.groupBy(*key).agg(F.min("node").alias("class"))
        return df.join(least, list(key)).select("node", "class")

    def refine(env) -> Relation:
        heard = env["near"].df.join(env["colour"].df.select(F.col("node").alias("src"), F.col("class")), "src")
        counts = heard.groupBy(F.col("dst").alias("node"), "class").agg(F.count(F.lit(1)).alias("n"))
        # Order does not matter to sums of hashes, so a hub's classes need not be listed.
        around = counts.groupBy("node").agg(
            *(F.sum(F.xxhash64(F.lit(seed), "class", "n").cast("decimal(38,0)")).alias(f"h{seed}") for seed in (1, 2)), F.count(F.lit(1)).alias("kinds")
        )
        both = env["colour"].df.join(around, "node", "left").withColumnRenamed("class", "own")
        both = both.na.fill(0, ["kinds"]).withColumns({h: F.coalesce(h, F.lit(0)) for h in ("h1", "h2")})
        return Relation(named(both, "own", "h1", "h2", "kinds"))

    def stable(env, before) -> bool:
        sizes.append(env["colour"].df.select("class").distinct().count())
        return len(sizes) > 1 and sizes[-1] == sizes[-2] if rounds is None else len(sizes) > rounds

    start = durable(named(labels.select("node", "label"), "label"))
    sizes.append(start.select("class").distinct().count())
    proc = Procedure().let("near", lambda env: Relation(near)).let("colour", lambda env: Relation(start))
    if rounds == 0:
        return start, sizes
    body = Procedure().let("colour", refine, reads=("near", "colour"))
    found = run(proc.loop(body, Until(stable, ("colour",)), keys=(("near", "src"),)).ret("colour"), Catalog(edges.sparkSession))
    return found.df, sizes


def top_per_group(df: DataFrame, group: str, order: list, k: int) -> DataFrame:
    """The first ``k`` rows of each group."""
    w = Window.partitionBy(group).orderBy(*order)
    return df.withColumn("_k", F.row_number().over(w)).where(F.col("_k") <= k).drop("_k")
