"""Registered queries against their SQL on the smallest tables."""

import random

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from graphloop.baselines import glue, reference
from graphloop.plans import compiler
from graphloop.sources import edges as views
from graphloop.workloads import batch

SF = "/root/testdata/sf0.001"


def by_sql(name, sf_dir=SF, **tables):
    """Rows of a query's SQL; ``tables`` are files that stand in for given ones."""
    db = duckdb.connect()
    for table in ("nation", "region", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings", "conversations"):
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{tables.get(table, f'{sf_dir}/{table}.parquet')}'")
    return sorted(db.execute(entry.oracle_sql()[name]).fetchall(), key=repr)


def by_spark(spark, name, sf_dir=SF):
    return sorted((tuple(r) for r in entry.queries()[name](spark, sf_dir).collect()), key=repr)


@pytest.mark.parametrize("name", ["adom_report", "glue_pindex", "edges_g9", "gnn_edge_update", "gnn_max_1", "gnn_mean_2", "gnn_readout"])
def test_query_equals_its_sql(spark, name):
    assert by_spark(spark, name) == by_sql(name)


def test_nearest_vectors_in_blocks(spark, tmp_path):
    """Copies, ties, vectors without direction and missing ones, over many blocks; and no lambda looks at each pair's coordinates."""
    rng = random.Random(5)
    rows = [(k, [rng.gauss(0, 1) for _ in range(8)], k % 3) for k in range(150)]
    rows += [(200 + k, [1.0] * 8, 0) for k in range(60)] + [(300 + k, [2.0] * 8, 0) for k in range(9)] + [(400, [0.0] * 8, 1), (401, None, 1), (402, None, 1)]
    path = f"{tmp_path}/embeddings.parquet"
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(path)
    want = by_sql("edges_g9", embeddings=f"{path}/*.parquet")
    for block in (7, 64, 1024):
        found = views.nearest_vectors(spark, str(tmp_path), block=block)
        assert sorted((tuple(r) for r in found.select("src", "dst", "rank").collect()), key=repr) == want
    assert "aggregate(" not in found._jdf.queryExecution().toString()
    few = views.nearest_vectors(spark, str(tmp_path), queries=spark.read.parquet(path).where("vec_id < 20"), block=16)
    assert sorted((tuple(r) for r in few.select("src", "dst", "rank").collect()), key=repr) == [r for r in want if r[0] < 20]


def test_glue_takes_graphs_of_any_number_of_edges(spark, monkeypatch):
    rng = random.Random(6)
    rows = sorted({(rng.randrange(40), rng.randrange(40)) for _ in range(200)})
    monkeypatch.setattr(reference, "MAX_EDGES", 50)
    authors = spark.createDataFrame([(k, k) for k in range(40)], "node long, author long")
    found, moved = glue.glue_pindex(spark.createDataFrame(rows, "src long, dst long"), authors, 40, rows=30)
    monkeypatch.undo()
    want = reference.pagerank(rows)
    assert {r.author: r.p_index for r in found.collect()} == pytest.approx(want)
    assert moved >= 16 * len(rows)
    assert glue.glue_pindex(spark.createDataFrame([], "src long, dst long"), authors)[0].count() == 0


@pytest.mark.parametrize("name", ["adom_bound", "batch_domain", "batch_exactness", "batch_local", "batch_per_value", "batch_reduce_intersect", "batch_rule1", "batch_rule2"])
def test_jobs_on_given_tables(spark, name, monkeypatch):
    """What was done on five made-up edges reads a given table by Spark, with the same job's result."""
    seen = set()
    read = views.read
    for module in (views, batch):
        monkeypatch.setattr(module, "read", lambda s, d, table: seen.add(table) or read(s, d, table))
    assert by_spark(spark, name) == by_sql(name)
    assert "lineitem" in seen


@pytest.mark.parametrize("slice_bytes", [100, 16_000_000])
def test_closure_in_slices_equals_rounds(spark, monkeypatch, slice_bytes):
    rng = random.Random(8)
    for rows in ([(rng.randrange(60), rng.randrange(60)) for _ in range(75)], [(k, k + 1) for k in range(40)], [(1, 1), (2, 3), (3, 2)], []):
        df = spark.createDataFrame(rows, "s long, o long")
        monkeypatch.setattr(compiler, "SLICE_BYTES", slice_bytes)
        found = [tuple(r) for r in compiler.closure(df).collect()]
        want = {(s, o) for s, _ in rows for o in reference.reach(rows, s)}
        assert set(found) == want and len(found) == len(want)
    monkeypatch.setattr(compiler, "_compose", None)  # no rounds
    assert by_spark(spark, "rec_ancestors") == by_sql("rec_ancestors")


def test_closure_stays_in_the_parts_of_the_graph(spark, monkeypatch):
    """Copies of a graph cost as many times the cells as there are copies, and no more; a circle is no detour."""
    one = [(k + 1, k) for k in range(90)] + [(k + 3, k) for k in range(0, 80, 7)] + [(200, 201), (201, 202), (202, 200), (200, 5), (300, 300)]
    monkeypatch.setattr(compiler, "SLICE_BYTES", 200)

    def cells(rows):
        graph = compiler._contracted(*np.array(rows, dtype=np.int64).T)
        found = compiler._slices(graph, 8)
        assert sum(many for _, many in found) == len({x for row in rows for x in row})
        spans = [(graph.until[graph.group[first + many - 1]] - graph.group[first], many) for first, many in found]
        assert all(rows * many <= 8 * 200 for rows, many in spans)
        return sum(int(rows) * many for rows, many in spans)

    six = [(s + 1000 * k, o + 1000 * k) for k in range(6) for s, o in one]
    assert cells(six) <= 8 * cells(one)
    monkeypatch.setattr(compiler, "CELLS", 500)
    monkeypatch.setattr(compiler, "SLICE_TARGETS", 8)
    found = [tuple(r) for r in compiler.closure(spark.createDataFrame(six, "s long, o long")).collect()]
    want = {(s, o) for s, _ in six for o in reference.reach(six, s)}
    assert set(found) == want and len(found) == len(want)
