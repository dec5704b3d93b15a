"""Procedures against in-memory references, in all modes; what loops read, move and leave behind; verdicts on batches."""

import os
import random
import time

import pytest
from pyspark.sql import functions as F

from graphloop.algorithms import procedures
from graphloop.algorithms.reach import graph_catalog
from graphloop.algorithms.vertex import busiest_source
from graphloop.baselines import reference
from graphloop.materialize import FORGETFUL, checkpoint_dir, checkpoint_files, durable, settings, steady
from graphloop.plans import batches
from graphloop.plans import query as q
from graphloop.plans import runtime
from graphloop.plans.catalog import Catalog
from graphloop.plans.compiler import compile_query
from graphloop.plans.parser import parse_procedure
from graphloop.plans.procedure import Let, Loop, Procedure, Until, validate
from graphloop.plans.rewrite import optimise
from graphloop.relation import Relation

SEED = 42


def graph(spark, seed, nodes=30, edges=70):
    rng = random.Random(seed)
    pairs = sorted({(rng.randrange(nodes), rng.randrange(nodes)) for _ in range(edges)})
    return pairs, spark.createDataFrame(pairs, "src long, dst long")


def expected(name, pairs, start):
    return {
        "bfs": lambda: reference.bfs(pairs, start),
        "sssp": lambda: reference.sssp([(s, d, 1.0) for s, d in pairs], start),
        "wcc": lambda: reference.wcc(pairs),
        "lcc": lambda: reference.lcc(pairs),
        "cdlp": lambda: reference.cdlp(pairs),
        "pr": lambda: reference.pagerank(pairs),
    }[name]()


@pytest.mark.parametrize("name", ["bfs", "sssp", "wcc", "lcc", "cdlp", "pr"])
def test_procedures_equal_references_in_all_modes(spark, name):
    proc = parse_procedure(procedures.text_of(name))
    assert validate(proc) == []
    pairs, df = graph(spark, SEED)
    want = {k: round(v, 9) for k, v in expected(name, pairs, busiest_source(df)).items()}
    for mode, how in (("plan", ""), ("inline", ""), ("batched", "lifted")):
        found = procedures.result(name, procedures.solve(name, df, mode=mode, how=how))
        assert {r[0]: round(r[1], 9) for r in found.collect()} == want, mode


def test_no_statement_is_a_function(spark):
    for text in [procedures.text_of(n) for n in procedures.SPLITS] + [procedures.P_INDEX]:
        todo = list(parse_procedure(text).statements)
        while todo:
            s = todo.pop()
            todo += s.body if isinstance(s, Loop) else ()
            assert not isinstance(s, Let) or not any(isinstance(n, q.Table) for n in q.walk(s.query))


def plans_of_rounds(spark, monkeypatch, task):
    """Text of the executed plan of every snapshot."""
    seen = []
    plain = runtime.durable

    def watched(df):
        with runtime.settings(spark, FORGETFUL):
            seen.append(df._jdf.queryExecution().executedPlan().toString())
        return plain(df)

    monkeypatch.setattr(runtime, "durable", watched)
    task()
    return seen


def test_rounds_read_snapshots_and_edges_stay_where_they_lie(spark, monkeypatch, tmp_path):
    monkeypatch.setattr("graphloop.materialize.SMALL_ROWS", 0)
    path = str(tmp_path / "ring.parquet")
    spark.range(40).select(F.col("id").alias("src"), ((F.col("id") + 1) % 40).alias("dst")).write.parquet(path)
    edges = spark.read.parquet(path)
    before = set(os.listdir(checkpoint_dir(spark).removeprefix("file:")))
    with runtime.settings(spark, {"spark.sql.autoBroadcastJoinThreshold": "-1"}):
        out = []
        plans = plans_of_rounds(spark, monkeypatch, lambda: out.append(procedures.solve("bfs", edges, 0)))
    rounds = plans[-30:]
    assert out[0].rounds == [40] and out[0].df.count() == 40
    assert not any("Scan parquet" in p for p in rounds)
    # One exchange a round: of what is sent. Levels are kept as a bounded number of snapshots.
    assert all(p.count("Exchange") == (0 if "SortMergeJoin" not in p else 1) for p in rounds)
    assert max(p.count("Scan ExistingRDD") for p in rounds) <= 2 + runtime.LOG_PIECES
    after = set(os.listdir(checkpoint_dir(spark).removeprefix("file:"))) - before
    assert len(after) <= 2 * runtime.LOG_PIECES + 4
    assert checkpoint_files(out[0].df)


def test_a_hub_is_left_to_adaptive_plans(spark, monkeypatch):
    monkeypatch.setattr("graphloop.materialize.SMALL_ROWS", 0)
    star = [(0, k) for k in range(1, 200)] + [(k, k + 1) for k in range(1, 20)]
    df = spark.createDataFrame(star, "src long, dst long")
    found = procedures.result("bfs", procedures.solve("bfs", df, 0)).collect()
    assert {r.node: r.level for r in found} == reference.bfs(star, 0)
    assert spark.conf.get("spark.sql.adaptive.enabled") == "true"


def test_a_time_limit_stops_a_running_job(spark):
    slow = F.udf(lambda x: time.sleep(20) or x, "long")
    proc = Procedure().let("x", lambda env: Relation(spark.range(1).select(slow("id").alias("v"))))
    proc.loop(Procedure().let("x", lambda env: env["x"]), Until(lambda env, before: True))
    began = time.time()
    with pytest.raises(runtime.TimeLimit):
        runtime.run(proc.ret("x"), Catalog(spark), timeout_s=2)
    assert time.time() - began < 15


def test_exact_means_batches_are_the_full_answer(spark):
    rng = random.Random(SEED)
    _, edges = graph(spark, 5, 8, 14)
    links = edges.toDF("node", "cite")
    env = {
        "links": Relation(links),
        "other": Relation(spark.createDataFrame([(2, 3), (4, 3), (7, 1)], "node long, weight long")),
        "both": Relation(edges.toDF("cite", "more")),
        "holey": Relation(spark.createDataFrame([(1, None), (2, 3)], "more long, cite long"), frozenset({"cite"})),
    }
    catalog = Catalog(spark)
    plan = batches.map_split(env, "cite", [], catalog)

    def some(depth):
        if depth == 0:
            return q.VarRef(rng.choice(list(env)))
        kind = rng.randrange(6)
        if kind < 2:
            return q.Join(some(depth - 1), some(depth - 1))
        if kind == 2:
            return q.Union(some(depth - 1), some(depth - 1))
        if kind == 3:
            return q.Project(some(depth - 1), (rng.choice(("node", "cite")),))
        if kind == 4:
            return q.Group(some(depth - 1), (rng.choice(("node", "cite")),), (("n", q.Agg("count")),))
        return q.Distinct(some(depth - 1))

    exact = 0
    for k in range(60):
        query = some(rng.randrange(1, 4))
        if batches.verdict(query, "cite", env, plan) == "EXACT" and exact < 8:
            exact += 1
            full = compile_query(query, env, catalog).df
            found = batches.eval_batches(query, plan, env, catalog, batches.reduce_union())[0].df.select(full.columns)
            assert sorted(map(str, found.collect())) == sorted(map(str, full.collect())), (k, query)
    assert exact >= 5
    union = q.Union(q.Project(q.VarRef("links"), ("node",)), q.Project(q.VarRef("other"), ("node",)))
    assert batches.verdict(union, "cite", env, plan) == "UNKNOWN"


def test_tuples_equal_the_product_of_domains(spark):
    a = Relation(spark.createDataFrame([(1, 10), (1, 11), (2, 10)], "x long, y long"))
    b = Relation(spark.createDataFrame([(1, 5), (2, 6)], "x long, z long"))
    c = Relation(spark.createDataFrame([(10,), (12,)], "y long"))
    env, catalog = {"a": a, "b": b, "c": c}, Catalog(spark)
    dx, dy = (1, 2), (10, 11, 12)
    for query in (q.Join(q.VarRef("a"), q.VarRef("b")), q.VarRef("b"), q.Union(q.Project(q.VarRef("a"), ("x",)), q.Project(q.VarRef("b"), ("x",)))):
        want = []
        for x in dx:
            for y in dy:
                part = {"a": Relation(a.df.where((F.col("x") == x) & (F.col("y") == y))), "b": Relation(b.df.where(F.col("x") == x)), "c": Relation(c.df.where(F.col("y") == y))}
                want += [str(r) for r in compile_query(query, part, catalog).df.collect()]
        found = batches.eval_tuples(query, env, catalog, ("x", "y"), ("a", "b", "c"))
        assert sorted(str(r) for r in found.df.select(compile_query(query, env, catalog).df.columns).collect()) == sorted(want)


def test_parts_that_no_round_changes_are_hoisted(spark):
    proc = optimise(parse_procedure("""
      LET seen = (SELECT (0 AS ?n) WHERE { });
      DO ( LET seen = (SELECT DISTINCT ?n WHERE { { QVALUES(seen) } UNION { SELECT (?m AS ?n) WHERE { ?n g:step ?k . QVALUES(seen) . ?k g:step ?m } } }); ) WHILE (TIMES 3);
      RETURN(seen);"""))
    loop = next(s for s in proc.statements if isinstance(s, Loop))
    assert not any(isinstance(n, q.Bgp) for s in loop.body for n in q.walk(s.query))
    edges = spark.createDataFrame([(k, k + 1) for k in range(9)], "src long, dst long")
    assert sorted(r.n for r in runtime.run(proc, graph_catalog(edges)).df.collect()) == [0, 2, 4, 6]


def test_components_take_few_rounds_on_long_ways(spark):
    rng = random.Random(SEED)
    names = rng.sample(range(10_000), 600)
    rows = list(zip(names, names[1:], strict=False))
    found = procedures.solve("wcc", spark.createDataFrame(rows, "src long, dst long"))
    assert {r[0]: r[1] for r in procedures.result("wcc", found).collect()} == dict.fromkeys(names, min(names))
    assert found.rounds[0] <= 7


def test_snapshots_of_self_joins_stay_plain(spark):
    df = durable(spark.range(100).withColumn("to", F.col("id") % 7))
    with settings(spark, steady(4)):
        for _ in range(9):
            df = durable(df.alias("a").join(df.alias("b"), F.col("a.to") == F.col("b.id")).select("a.id", F.col("b.to").alias("to")))
            plan = df._jdf.queryExecution().analyzed()
            assert len(plan.outputPartitioning().toString()) < 400
            assert plan.stats().sizeInBytes() < 2**64
        assert sorted(tuple(r) for r in df.collect()) == [(k, k % 7) for k in range(100)]


def test_tasks_have_no_time_limit(spark, monkeypatch):
    from graphloop.workloads import tasks

    monkeypatch.setattr(tasks, "LIMIT_S", 1e-9)
    assert tasks.QUERIES["stress_batched_cdlp"](spark, "/root/testdata/sf0.001").count() == 1473
    assert tasks.QUERIES["proc_wcc_g5"](spark, "/root/testdata/sf0.001").count() == 158


def test_batches_do_not_deal_the_edges_again(spark, monkeypatch):
    monkeypatch.setattr("graphloop.materialize.SMALL_ROWS", 0)
    plans = []
    kept = runtime.durable
    monkeypatch.setattr(batches, "durable", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or kept(df))
    pairs, df = graph(spark, SEED, 300, 900)
    start = busiest_source(df)
    found = procedures.result("bfs", procedures.solve("bfs", df, mode="batched", buckets=2))
    assert {r[0]: r[1] for r in found.collect()} == reference.bfs(pairs, start)
    assert plans and all("node" in p for p in plans)
    assert all(p.count("Exchange") <= 1 for p in plans)
