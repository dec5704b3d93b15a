"""Durable snapshots: every place where lineage is cut goes through this module.

Snapshots live in the shared folder that the cluster names in ``spark.checkpoint.dir``;
a folder of our own is made only where that setting is absent (tests, notebooks).
Local checkpoints are never used: their blocks die with an executor.
"""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SMALL_ROWS = 50_000
ROWS_A_PART = 2_000_000
VAST = 2**62
# A checkpoint remembers constraints of its plan, and a union of checkpoints fails on those that name columns it lost.
FORGETFUL = {"spark.sql.constraintPropagation.enabled": "false"}


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder for snapshots, set on the context if nothing has set it yet."""
    sc = spark.sparkContext
    known = sc.getCheckpointDir()
    if known:
        return known
    folder = sc.getConf().get("spark.checkpoint.dir")
    if not folder:
        if sc.master.startswith("local"):
            folder = tempfile.mkdtemp(prefix="graphloop-")
        else:
            folder = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
    sc.setCheckpointDir(folder)
    return sc.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """An eager reliable checkpoint; Spark's cleaner may drop it once nothing refers to it."""
    checkpoint_dir(df.sparkSession)
    with settings(df.sparkSession, FORGETFUL):
        return _slim(df.checkpoint(eager=True))


def _slim(df: DataFrame) -> DataFrame:
    """The same checkpoint, which remembers no more of its plan than the next plan can use.

    A join is taken to lie as both of its sides do, and to be as large as their product. A loop that joins a variable with
    itself would double the one and square the other in every round, until planning takes longer than the work: of what is
    said several times about how rows lie, each is kept once, and a size beyond all bounds is unknown.
    """
    spark, jvm = df.sparkSession, df.sparkSession.sparkContext._jvm
    plan = df._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return df
    lies = plan.outputPartitioning()
    several = lies.getClass().getSimpleName() == "PartitioningCollection"
    if not several and plan.stats().sizeInBytes() <= VAST:
        return df
    if several:
        each, todo = {}, [lies]
        while todo:
            one = todo.pop()
            if one.getClass().getSimpleName() == "PartitioningCollection":
                inner = one.partitionings()
                todo += [inner.apply(k) for k in range(inner.size())]
            else:
                each.setdefault(one.toString(), one)
        first, *more = each.values()
        lies = first
        if more:
            listed = jvm.java.util.ArrayList()
            for one in (first, *more):
                listed.add(one)
            lies = jvm.org.apache.spark.sql.catalyst.plans.physical.PartitioningCollection(jvm.scala.jdk.javaapi.CollectionConverters.asScala(listed).toSeq())
    none = getattr(getattr(jvm.scala, "None$"), "MODULE$")
    plain = jvm.org.apache.spark.sql.execution.LogicalRDD(
        plan.output(), plan.rdd(), lies, plan.outputOrdering(), plan.isStreaming(), none, spark._jsparkSession, none, none
    )
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plain), spark)


def stored(df: DataFrame, *partition_by: str) -> DataFrame:
    """A compressed columnar snapshot in the shared folder, for wide rows or column pruning."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark).rstrip('/')}/table-{uuid.uuid4().hex}"
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]) -> Iterator[None]:
    """Run-time settings for a while; what was set before comes back, whatever happens."""
    before = {name: spark.conf.get(name, None) for name in values}
    try:
        for name, value in values.items():
            spark.conf.set(name, value)
        yield
    finally:
        for name, value in before.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)


def parts_for(spark: SparkSession, rows: int) -> int:
    """Partitions of a loop over ``rows`` rows: one if they are few, else the session's number or as many as rows need."""
    if rows <= SMALL_ROWS:
        return 1
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // ROWS_A_PART))


def steady(parts: int) -> dict[str, str]:
    """Settings under which a layout by key outlives a checkpoint, so what lies by the join key is not dealt out again.

    Adaptive plans forget it. In one partition nothing is exchanged at all, so broadcasts would only cost jobs.
    """
    fixed = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts)}
    return fixed | ({"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.join.preferSortMergeJoin": "false"} if parts == 1 else {})


def has_hub(df: DataFrame, key: str, rows: int, parts: int) -> bool:
    """Whether one value of ``key`` has more rows than four partitions should; such a key must be left to skew handling."""
    if parts == 1:
        return False
    most = df.groupBy(key).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    return most > 4 * max(rows // parts, 1)


def laid_out(df: DataFrame, key: str | None, parts: int) -> DataFrame:
    """A reliable checkpoint, dealt by ``key`` into ``parts`` partitions in a way that later joins on it can see."""
    with settings(df.sparkSession, steady(parts)):
        dealt = df.coalesce(1) if parts == 1 else df.repartition(parts, key) if key else df
        return durable(dealt)


def checkpoint_files(df: DataFrame) -> frozenset:
    """Folders of the checkpoints that a plan reads."""
    found, todo = set(), [df._jdf.queryExecution().analyzed()]
    while todo:
        node = todo.pop()
        if node.getClass().getSimpleName() == "LogicalRDD":
            at = node.rdd().getCheckpointFile()
            if at.isDefined():
                found.add(at.get())
        children = node.children()
        todo += [children.apply(k) for k in range(children.size())]
    return frozenset(found)


def discard(spark: SparkSession, folders) -> None:
    """Deletes folders of snapshots that nothing reads any more."""
    sc = spark.sparkContext
    for folder in folders:
        path = sc._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Lets the cleaner drop the shuffle files of plans that nothing refers to any more."""
    for _ in range(2):  # what Python lets go of in the first pass, the JVM finds in the second
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.2)
