"""Sources, sinks and streams."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import functions as F

from graphloop.algorithms.vertex import bfs, busiest_source
from graphloop.materialize import checkpoint_dir
from graphloop.plans.catalog import tables_catalog
from graphloop.plans.parser import parse_procedure
from graphloop.plans.runtime import run
from graphloop.sources import files
from graphloop.sources.edges import read
from graphloop.sources.endpoint import EndpointSource
from graphloop.streaming import events as stream
from graphloop.terms import sql_id
from graphloop.workloads import sqltext as sql
from graphloop.workloads.analytics import check, differ, pairs, zero

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return register


def folder(spark) -> str:
    """A fresh path in the shared folder."""
    return f"{checkpoint_dir(spark).rstrip('/')}/io-{uuid.uuid4().hex}"


@add("io_ntriples", f"SELECT {sql_id('nation', 'n_nationkey')}::VARCHAR AS s, 'nation_name' AS p, n_name AS o FROM nation UNION ALL SELECT {sql_id('document', 'doc_id')}::VARCHAR, 'language', lang FROM documents")
def io_ntriples(spark, sf_dir):
    path = folder(spark)
    files.write_ntriples(tables_catalog(spark, sf_dir).triples(["nation_name", "language"]), path)
    return files.read_ntriples(spark, path)


@add("io_edgelist", f"SELECT src, dst FROM ({sql.pairs('g2')})")
def io_edgelist(spark, sf_dir):
    path = folder(spark)
    files.write_edges(pairs(spark, sf_dir, "g2"), path)
    return files.read_edges(spark, path)


@add("io_formats", zero("io_formats"))
def io_formats(spark, sf_dir):
    e, lost = pairs(spark, sf_dir, "g3"), 0
    for kind in ("csv", "json", "orc", "parquet"):
        path = folder(spark)
        e.write.format(kind).save(path)
        lost += differ(e, spark.read.schema("src long, dst long").format(kind).load(path))
    return check("io_formats", lost, spark)


@add("io_endpoint", "SELECT * FROM (VALUES ('a', 'near', 'b'), ('b', 'near', 'c'), ('c', 'far', 'a')) t(s, p, o)")
def io_endpoint(spark, sf_dir):
    spark.dataSource.register(EndpointSource)
    rows = json.dumps([["a", "near", "b"], ["b", "near", "c"], ["c", "far", "a"]])
    return spark.read.format("endpoint").option("rows", rows).option("pages", "2").load()


@add("sql_view_result", "SELECT count(*)::BIGINT AS n FROM customer WHERE c_nationkey = 5")
def sql_view_result(spark, sf_dir):
    found = run(parse_procedure("LET c = (SELECT ?c WHERE { ?c t:customer_nation <nation/5> }); RETURN(c);"), tables_catalog(spark, sf_dir)).df
    found.createOrReplaceTempView("procedure_result")
    return spark.sql("SELECT count(*) AS n FROM procedure_result")


# The plans that streams run, over the whole table


def _events(spark, sf_dir):
    return stream.with_time(read(spark, sf_dir, "events"))


def _plain(df):
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("window_start", "window_end")})


@add("stream_dedupe", "SELECT event_id, user_id FROM events")
def stream_dedupe(spark, sf_dir):
    twice = _events(spark, sf_dir)
    return stream.deduplicated(twice.union(twice)).select("event_id", "user_id")


@add("stream_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') AS window_start, time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') + INTERVAL 1 HOUR AS window_end, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    return _plain(stream.windowed_counts(_events(spark, sf_dir), "1 hour"))


@add("stream_sliding", "SELECT s AS window_start, s + INTERVAL 1 HOUR AS window_end, event_type, count(*)::BIGINT AS n FROM (SELECT event_type, time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01') - (INTERVAL 30 MINUTE * d) AS s FROM events, (SELECT unnest([0, 1]) AS d)) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return _plain(stream.windowed_counts(_events(spark, sf_dir), "1 hour", "30 minutes"))


@add(
    "stream_session",
    """WITH e AS (SELECT user_id, ts, coalesce(ts > lag(ts) OVER w + INTERVAL 1 HOUR, true) OR ts = lag(ts) OVER w + INTERVAL 1 HOUR AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
      g AS (SELECT *, sum(fresh::INT) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
      SELECT user_id, min(ts) AS window_start, max(ts) + INTERVAL 1 HOUR AS window_end, count(*)::BIGINT AS n FROM g GROUP BY user_id, k""",
)
def stream_session(spark, sf_dir):
    return _plain(stream.sessions(_events(spark, sf_dir), "1 hour"))


@add("stream_run", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def stream_run(spark, sf_dir):
    """A stream that reads the table's files as they are and ends when all are read."""
    path = folder(spark)
    read(spark, sf_dir, "events").repartition(3).write.parquet(path)
    counts = stream.event_stream(spark, path).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return stream.run_to_memory(counts, f"counts_{uuid.uuid4().hex[:8]}", "complete", folder(spark))


@add("stream_reach_equals_batch", zero("stream_reach_equals_batch"))
def stream_reach_equals_batch(spark, sf_dir):
    e = pairs(spark, sf_dir, "g2")
    start = busiest_source(e)
    return check("stream_reach_equals_batch", differ(stream.reach_in_batches(e, start, 3), bfs(e, start).select("node")), spark)


