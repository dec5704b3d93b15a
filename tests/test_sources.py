"""Files, streams and the entry module."""

import subprocess
import sys
from pathlib import Path

import pytest

from graphloop.sources import files
from graphloop.sources.edges import read
from graphloop.streaming import events as stream

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parent.parent


def test_triples_round_trip(spark, tmp_path):
    rows = [("a", "p", 'x "quoted" \\ back'), ("b", "q", "two\nlines"), ("c", "p", "é")]
    df = spark.createDataFrame(rows, "s string, p string, o string")
    files.write_ntriples(df, str(tmp_path / "t"))
    assert sorted(map(tuple, files.read_ntriples(spark, str(tmp_path / "t")).collect())) == sorted(rows)


def test_weighted_edges_round_trip(spark, tmp_path):
    df = spark.createDataFrame([(1, 2, 0.5), (2, 3, 1.25)], "src long, dst long, weight double")
    files.write_edges(df, str(tmp_path / "e"))
    assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / "e"), weighted=True).collect())) == [(1, 2, 0.5), (2, 3, 1.25)]
    assert files.result_json(df.limit(1)).count() == 1


@pytest.fixture(scope="module")
def event_files(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events") / "files")
    read(spark, SF, "events").repartition(2).write.parquet(path)
    return path


def test_streams_equal_batches(spark, event_files, tmp_path):
    batch = stream.with_time(read(spark, SF, "events"))
    tumbling = stream.run_to_memory(stream.windowed_counts(stream.event_stream(spark, event_files), "1 hour", delay="400 days"), "tumbling", "complete", str(tmp_path / "a"))
    expected = stream.windowed_counts(batch, "1 hour")
    assert sorted(map(tuple, tumbling.collect())) == sorted(map(tuple, expected.collect()))
    once = stream.deduplicated(stream.event_stream(spark, event_files), "400 days").select("event_id")
    assert stream.run_to_memory(once, "once", "append", str(tmp_path / "b")).count() == batch.count()


def test_lineage_keeps_state_between_batches(spark, tmp_path):
    folder = tmp_path / "in"
    for k, rows in enumerate(([(1, "2024-01-01 00:00:00", 5), (2, "2024-01-01 01:00:00", 5)], [(3, "2024-01-01 02:00:00", 5), (4, "2024-01-01 02:00:00", 6)])):
        df = spark.createDataFrame([(e, t, u, "view", 1.0, "{}") for e, t, u in rows], "event_id long, t string, user_id long, event_type string, value double, props string")
        df.selectExpr("event_id", "CAST(t AS TIMESTAMP_NTZ) AS ts", "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(str(folder))
    found = stream.run_to_memory(stream.lineage(stream.event_stream(spark, str(folder))), "lineage", "append", str(tmp_path / "c"))
    assert sorted(map(tuple, found.collect())) == [(2, 1), (3, 2)]


def test_parents_as_a_stream(spark, event_files, tmp_path):
    batch = stream.parents(stream.with_time(read(spark, SF, "events")), 6)
    live = stream.run_to_memory(stream.parents(stream.event_stream(spark, event_files), 10_000), "parents", "append", str(tmp_path / "d"))
    assert {tuple(r) for r in batch.collect()} <= {tuple(r) for r in live.collect()}


def test_every_oracle_has_its_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 150


def test_library_stands_without_the_text_folder(tmp_path):
    import shutil

    shutil.copytree(ROOT / "graphloop", tmp_path / "graphloop", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); e.oracle_sql(); assert 'pr_g1' in q and 'pipeline' not in q and not any(n.startswith('op1') for n in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": ""})
