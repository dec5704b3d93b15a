"""Mixing sources to target weights by weighted fair queueing.

Every source is a queue of its documents in shuffled order, repeated for a bounded number of
epochs. A document's virtual finish time is the source's cumulative size, this document
included, divided by the source's target; the mix is the global order of finish times, cut
where the total budget is used up. All sources then advance in proportion to their targets.

Only DataFrame functions are used. Cumulative sums are taken on two levels (sums of buckets,
then rows within a bucket), so neither a source with a third of all rows nor the global order
meets in one task: the shuffle order is cut by its leading hex digits, the finish times by
ranges of equal width, which hold about equal numbers of words because all queues are served
at constant rates.
Ranges that begin when the budget is used up are left out before rows are dealt to ranges, so the
copies that come too late, which may be most, meet in no task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphloop.llm.text import word_count
from graphloop.materialize import stored

ROWS_A_BUCKET = 10_000
MAX_RANGES = 16_384
LATE = 4


def source_targets(sizes: DataFrame, weights: list[int], max_epochs: int) -> DataFrame:
    """(source, source_size, rank, target) from rows (source, size).

    Sources in code-point order, null last, take ``weights`` in turn and share all words. No
    source gets more than ``max_epochs`` times its size; the excess goes to the others by
    weight until none is above. In order of size over weight the capped sources come first,
    so one pass of running sums finds the level.
    """
    one = F.lit(0)
    sums = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.partitionBy(one).orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*(F.lit(int(w)).cast("long") for w in weights)), (F.pmod(F.col("rank") - 1, F.lit(len(weights))) + 1).cast("int"))
    ranked = sums.withColumn("rank", F.row_number().over(order)).withColumn("weight", weight)
    ranked = ranked.withColumn("cap", F.col("source_size") * max_epochs)
    by_ratio = Window.partitionBy(one).orderBy((F.col("cap").cast("double") / F.col("weight")), "rank")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy(one)
    level = (
        ranked.withColumn("room", F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("weights", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("capped", F.col("cap").cast("double") * F.col("weights") <= F.col("weight").cast("double") * F.col("room"))
    )
    free = (
        level.withColumn("free", ~F.col("capped"))
        .withColumn("_room", F.max(F.when(F.col("free"), F.struct("weights", "room"))).over(every))
    )
    share = (F.col("weight") * F.col("_room.room")).cast("double") / F.col("_room.weights").cast("double")
    target = F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(share)
    return free.select("source", "source_size", F.col("rank").cast("long").alias("rank"), target.alias("target"))


def mix(
    df: DataFrame,
    id_col: str = "doc_id",
    source_col: str = "source",
    text_col: str = "text",
    weights: tuple[int, ...] = (5, 2, 1),
    max_epochs: int = 3,
    seed: str = "mix",
) -> DataFrame:
    """One row for each row of ``df``: row_id, id, source, size, source_size, target, copies, taken.

    ``copies`` is how often the mix takes the document, ``taken`` its words with repeats. The
    shuffle is a hash of seed and id, so reruns agree; ties go by id, size and row. Null texts
    have size 0 and are never queued; a null source is a source of its own, last in order; rows
    that repeat an id queue one by one. A source without words has target 0; an empty table
    gives an empty result. Other columns of ``df`` do not matter.
    """
    if max_epochs < 1 or any(w <= 0 for w in weights):
        raise ValueError("max_epochs and weights must be positive")
    base = df.select(
        F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size")
    )
    base = base.withColumn("turn", F.md5(F.concat_ws(":", F.lit(seed), F.coalesce(F.col("id").cast("string"), F.lit("null")))))
    base = stored(base.withColumn("row_id", F.monotonically_increasing_id()))
    n_rows = base.count()
    digits = 1
    while n_rows > ROWS_A_BUCKET * 16**digits and digits < 6:
        digits += 1
    targets = stored(source_targets(base, list(weights), max_epochs))
    known = base.join(F.broadcast(targets) if targets.count() < 100_000 else targets, base["source"].eqNullSafe(targets["source"])).drop(targets["source"])

    queued = known.where(F.col("size") > 0).select("row_id", "id", "size", "turn", "rank", "source_size", "target")
    queued = queued.withColumn("cell", F.substring("turn", 1, digits))
    starts = _starts(queued, ["rank", "cell"], Window.partitionBy("rank").orderBy("cell"))
    inside = Window.partitionBy("rank", "cell").orderBy("turn", "id", "size", "row_id").rowsBetween(Window.unboundedPreceding, 0)
    queued = queued.join(starts, ["rank", "cell"]).withColumn("upto", F.col("start") + F.sum("size").over(inside)).drop("start", "cell")

    ranges = max(1, min(MAX_RANGES, n_rows // ROWS_A_BUCKET))
    epoch = F.explode(F.sequence(F.lit(0), F.lit(max_epochs - 1))).alias("epoch")
    copies = queued.select("*", epoch).withColumn(
        "finish", (F.col("epoch") * F.col("source_size") + F.col("upto")).cast("double") / F.col("target")
    )
    copies = copies.withColumn("range", F.least(F.floor(F.col("finish") * ranges), F.lit(LATE * ranges)))
    budget = base.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("budget"))
    heads = _starts(copies, ["range"], Window.partitionBy(F.lit(0)).orderBy("range"))
    in_range = Window.partitionBy("range").orderBy("finish", "rank", "turn", "id", "size", "row_id", "epoch").rowsBetween(Window.unboundedPreceding, 0)
    # At most LATE * MAX_RANGES + 1 rows, whatever the corpus. A document has a word at least: none fits from the budget on.
    open_ranges = F.broadcast(heads.join(F.broadcast(budget)).where(F.col("start") < F.col("budget")))
    served = (
        copies.join(open_ranges, "range")
        .withColumn("total", F.col("start") + F.sum("size").over(in_range))
        .where(F.col("total") <= F.col("budget"))
        .groupBy("row_id")
        .agg(F.count(F.lit(1)).alias("copies"))
    )
    counted = F.coalesce(F.col("copies"), F.lit(0))
    return known.join(served, "row_id", "left").select(
        "row_id", "id", "source", "size", "source_size", "target", counted.alias("copies"), (counted * F.col("size")).alias("taken")
    )


def _starts(df: DataFrame, keys: list[str], order) -> DataFrame:
    """Words before each bucket."""
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    sums = df.groupBy(*keys).agg(F.sum("size").alias("words"))
    return sums.select(*keys, F.coalesce(F.sum("words").over(before), F.lit(0)).alias("start"))


def digest(mixed: DataFrame) -> DataFrame:
    """The contract's columns."""
    return mixed.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")
