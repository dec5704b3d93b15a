"""Event streams as growing graphs. Each function takes a stream or a table with the columns of ``events``."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphloop.materialize import durable, stored

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """A stream of Parquet files of events; the time becomes a zoned one in UTC, as watermarks need."""
    raw = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(path)
    return with_time(raw)


def with_time(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Events once by id; what comes later than ``delay`` is dropped."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(events: DataFrame, size: str, slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(window_start, window_end, event_type, n) of tumbling or sliding windows."""
    if events.isStreaming:
        events = events.withWatermark("ts", delay)
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    counts = events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counts.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "event_type", "n")


def sessions(events: DataFrame, gap: str, delay: str = "1 day") -> DataFrame:
    """(user_id, window_start, window_end, n) of sessions by user."""
    if events.isStreaming:
        events = events.withWatermark("ts", delay)
    counts = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return counts.select("user_id", F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "n")


def lineage(events: DataFrame) -> DataFrame:
    """(src, dst): each event to the previous one of its user, by state kept per user; stream only."""

    def link(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        for frame in frames:
            ids = frame.sort_values(["ts", "event_id"])["event_id"].tolist()
            before = ([last] if last is not None else []) + ids[:-1]
            own = ids if last is not None else ids[1:]
            last = ids[-1]
            yield pd.DataFrame({"src": own, "dst": before[: len(own)]})
        if last is not None:
            state.update((last,))

    return events.select("user_id", "ts", "event_id").groupBy("user_id").applyInPandasWithState(
        link, "src long, dst long", "last long", "append", GroupStateTimeout.NoTimeout
    )


def parents(events: DataFrame, hours: int = 6) -> DataFrame:
    """(src, dst) of events of one user less than ``hours`` apart, as a stream-stream interval join."""
    later, earlier = events.alias("a"), events.alias("b")
    if events.isStreaming:
        later, earlier = events.withWatermark("ts", f"{hours} hours").alias("a"), events.withWatermark("ts", f"{hours} hours").alias("b")
    near = F.expr(f"a.user_id = b.user_id AND b.ts < a.ts AND b.ts > a.ts - INTERVAL {hours} HOURS")
    return later.join(earlier, near).select(F.col("a.event_id").alias("src"), F.col("b.event_id").alias("dst"))


class GrowingReach:
    """Reachability that goes on from its last state when edges are added; edges are never taken back."""

    def __init__(self, spark: SparkSession, source: int):
        self.source = source
        self.edges: DataFrame = spark.createDataFrame([], "src long, dst long")
        self.known: DataFrame = spark.createDataFrame([(source,)], "node long")

    def add(self, edges: DataFrame) -> DataFrame:
        """The new set of reached nodes (node), the source included."""
        self.edges = stored(self.edges.union(edges.select("src", "dst")).distinct())
        frontier = self.known
        while True:
            found = self.edges.join(frontier.withColumnRenamed("node", "src"), "src").select(F.col("dst").alias("node")).distinct()
            frontier = durable(found.join(self.known, "node", "left_anti"))
            if frontier.isEmpty():
                return self.known
            self.known = durable(self.known.union(frontier))


def reach_in_batches(edges: DataFrame, source: int, batches: int) -> DataFrame:
    """The same as reaching over all edges, edges arriving in ``batches`` parts."""
    growing = GrowingReach(edges.sparkSession, source)
    out = growing.known
    for b in range(batches):
        out = growing.add(edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(batches)) == b))
    return out


def run_to_memory(stream: DataFrame, name: str, mode: str, folder: str) -> DataFrame:
    """Runs a stream over what is there and gives its result as a table."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", folder).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


__all__ = ["GrowingReach", "deduplicated", "event_stream", "lineage", "parents", "reach_in_batches", "run_to_memory", "sessions", "windowed_counts", "with_time"]
