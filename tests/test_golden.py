"""Worked examples, golden values and hand-made inputs."""

import random

import pytest
from pyspark.sql import functions as F

from graphloop.algorithms import components, neural, pagerank, structure, turing, vertex
from graphloop.algorithms.reach import graph_catalog, reach_avoiding
from graphloop.baselines import reference
from graphloop.measure import graph_size, measure, rank_error
from graphloop.plans.procedure import Times
from graphloop.sources import edges as views
from graphloop.streaming.events import reach_in_batches

SAMPLE = [(2, 1), (3, 1), (4, 1), (4, 5), (1, 5)]
SF = "/root/testdata/sf0.001"


def graph(spark, rows, schema="src long, dst long"):
    return spark.createDataFrame(rows, schema)


def as_dict(df):
    return {r[0]: r[1] for r in df.collect()}


def random_edges(seed, nodes=30, n=70):
    rng = random.Random(seed)
    return [(rng.randrange(nodes), rng.randrange(nodes)) for _ in range(n)]


def test_worked_example(spark):
    e = graph(spark, SAMPLE)
    env = pagerank.run(pagerank.pagerank_procedure(until=Times(1)), graph_catalog(e)).env
    assert as_dict(env["sent"].df.selectExpr("to", "CAST(gain AS DOUBLE)")) == pytest.approx({1: 0.425, 5: 0.255})
    assert env["dealt"].df.first()[0] * 5 == pytest.approx(0.32)
    assert as_dict(env["held"].df.selectExpr("node", "CAST(rank AS DOUBLE)")) == pytest.approx({1: 0.489, 2: 0.064, 3: 0.064, 4: 0.064, 5: 0.319})
    ten = as_dict(pagerank.pagerank(e).df)
    assert ten == pytest.approx({1: 0.307301170, 5: 0.400568750, 2: 0.097376693, 3: 0.097376693, 4: 0.097376693}, abs=1e-9)


def test_graph_sizes(spark):
    expected = {"g1": (25, 50), "g2": (139, 1903), "g3": (45, 46), "g4": (87, 67), "g5": (158, 91), "g6": (24, 47), "g7": (1473, 5622), "g8": (305, 279)}
    for name, sizes in expected.items():
        assert tuple(graph_size(views.GRAPHS[name](spark, SF)).first()) == sizes


def test_pair_explosion_is_refused(spark, monkeypatch):
    monkeypatch.setattr(views, "PAIR_LIMIT", 10)
    with pytest.raises(ValueError, match="narrow the topic"):
        views.brand_citation(spark, SF)
    assert measure(lambda: views.brand_citation(spark, SF))["status"] == "skipped"


@pytest.mark.parametrize("seed", [1, 2])
def test_random_graphs_equal_the_reference(spark, seed):
    rows = random_edges(seed)
    simple = sorted(set(rows))
    e = graph(spark, rows)
    s = graph(spark, simple)
    start = rows[0][0]
    assert as_dict(vertex.bfs(e, start)) == reference.bfs(rows, start)
    weighted = [(a, b, float((a * 7 + b) % 5)) for a, b in simple]
    assert as_dict(vertex.sssp(graph(spark, weighted, "src long, dst long, weight double"), start, "weight")) == reference.sssp(weighted, start)
    expected = reference.wcc(rows)
    for options in ({}, {"local": False}, {"method": "minlabel"}):
        assert as_dict(structure.wcc(e, **options)) == expected
    assert as_dict(structure.lcc(e)) == pytest.approx(reference.lcc(rows))
    assert as_dict(structure.cdlp(s, 4)) == reference.cdlp(simple, 4)
    assert as_dict(pagerank.pagerank(e).df) == pytest.approx(reference.pagerank(rows))
    assert rank_error(pagerank.pagerank(e).df, reference.pagerank(rows)) < 1e-12
    blocked = {3, 4}
    got = reach_avoiding(e, start, spark.createDataFrame([(b,) for b in blocked], "node long"))
    assert {r[0] for r in got.df.collect()} == reference.reach(rows, start, blocked)
    labels = {v: v % 2 for pair in rows for v in pair}
    colours = structure.weisfeiler_lehman(e, spark.createDataFrame(list(labels.items()), "node long, label long"), 3)[0]
    assert as_dict(colours) == reference.weisfeiler_lehman(rows, labels, 3)
    assert {r[0] for r in reach_in_batches(e, start, 2).collect()} == set(reference.bfs(rows, start))


def test_components_in_parts(spark):
    rows = random_edges(9, 200, 150)
    roots, rounds = components.contract(graph(spark, rows), part_edges=20)
    assert rounds >= 1
    expected = reference.wcc(rows)
    assert as_dict(roots) == {v: c for v, c in expected.items() if v != c}


def test_hand_made_graphs(spark):
    none = graph(spark, [])
    assert all(f(none).count() == 0 for f in (structure.wcc, structure.lcc, structure.cdlp, lambda e: pagerank.pagerank(e).df))
    loop = graph(spark, [(1, 1)])
    assert as_dict(structure.wcc(loop)) == {1: 1} and as_dict(vertex.bfs(loop, 1)) == {1: 0} and as_dict(structure.lcc(loop)) == {1: 0.0}
    once, twice = graph(spark, [(1, 2)]), graph(spark, [(1, 2), (1, 2)])
    assert as_dict(pagerank.out_degree(twice)) == {1: 2}
    assert as_dict(pagerank.pagerank(once).df) == pytest.approx(as_dict(pagerank.pagerank(twice).df))
    hanging = as_dict(pagerank.pagerank(graph(spark, [(1, 2), (1, 3)])).df)
    assert sum(hanging.values()) == pytest.approx(1) and hanging[2] == pytest.approx(hanging[3])
    detour = graph(spark, [(1, 2, 5.0), (1, 3, 1.0), (3, 2, 1.0)], "src long, dst long, weight double")
    assert as_dict(vertex.sssp(detour, 1, "weight"))[2] == 2.0 and as_dict(vertex.bfs(detour, 1))[2] == 1
    assert as_dict(vertex.bfs(graph(spark, [(1, 2), (3, 4)]), 1, unreachable="max"))[4] == 2**63 - 1
    tie = graph(spark, [(1, 2), (3, 2)])
    assert as_dict(structure.cdlp(tie, 1))[2] == 1
    star = graph(spark, [(0, k) for k in range(1, 6)])
    same = spark.createDataFrame([(k, 0) for k in range(6)], "node long, label long")
    assert structure.weisfeiler_lehman(star, same)[0].select("class").distinct().count() == 2
    assert as_dict(vertex.bfs(graph(spark, [(1, 2)]), 99)) == {99: 0}


def test_layers_respect_colour_classes(spark):
    rows = sorted(set(random_edges(3)))
    e = graph(spark, rows)
    nodes = sorted({v for p in rows for v in p})
    labels = {v: v % 2 for v in nodes}
    one_hot = spark.createDataFrame([(v, [1.0 - k, float(k)]) for v, k in labels.items()], "node long, x array<double>")
    out = neural.gnn(e, one_hot, [neural.Layer("sum", 0.5, 0.25), neural.Layer("mean", 1.0, 1.0, act="tanh")], undirected=True)
    vectors = {}
    for r in out.collect():
        vectors.setdefault(r.node, {})[r.pos] = r.value
    colours = reference.weisfeiler_lehman(rows, labels, 2)
    for v in nodes:
        assert vectors[v] == pytest.approx(vectors[colours[v]], abs=1e-9)


def test_machines(spark):
    for word, accepted in (("", True), ("1", False), ("11", True)):
        assert (not turing.run_machine(turing.PARITY, word, spark).df.isEmpty()) == accepted
    tape = as_dict(turing.run_machine(turing.BINARY_INCREMENT, "111", spark).df)
    assert tape == {0: "0", 1: "0", 2: "0", 3: "1"}


def test_parallel_vertex_program_takes_the_better(spark):
    e = graph(spark, [(1, 2), (2, 3), (1, 3)])
    widest = vertex.vertex_program(e, spark.createDataFrame([(1, 9.0)], "node long, value double"), F.col("value") - 1, F.max, lambda new, old: new > old)
    assert as_dict(widest.df) == {1: 9.0, 2: 8.0, 3: 8.0}


def test_sql_ancestors_of_a_long_chain(spark):
    from graphloop.baselines.glue import sql_ancestors

    chain = [(k, k - 1) for k in range(1, 60)]
    edges = spark.createDataFrame([*chain, (101, 102), (102, 103), (103, 101)], "src long, dst long")
    found = {tuple(r) for r in sql_ancestors(edges).collect()}
    assert found == {(a, b) for a in range(60) for b in range(a)} | {(a, b) for a in (101, 102, 103) for b in (101, 102, 103)}
    assert sql_ancestors(edges.where("false")).count() == 0
