"""Line dedup: levelled sorted runs of line keys; a new batch merge-anti-joins them.

A run is a table (h1, h2, n_docs), sorted by the 128-bit key hash, of how many documents of
its batches hold a line. A batch is added in three steps: its distinct keys per document are
counted; keys that the runs already settle (their count has reached the threshold) are
anti-joined away; what is left is written as a new run of level 0. When a level holds
``fanout`` runs they are compacted: summed into one run of the next level. A line is frequent
once its counts over all runs reach the threshold, so settled keys stay settled.

Only DataFrame functions are used. Counting is combined before the shuffle, so a line found
in every document costs one row per task. Documents and their line keys meet by a join on the
document, never by a broadcast. Frequent keys meet the documents that hold them by a join on the
key, but for the hottest: few can be that frequent, whatever the size of the corpus, so they are broadcast and
their rows stay where they are (``holders``).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.llm.text import fold_ascii, sha256_hex, strip, unused
from graphloop.materialize import stored

KEY = ["h1", "h2"]
HOT_SHARE = 1_000


def line_key(line: Column) -> Column:
    """Stripped of separators, A-Z folded."""
    return fold_ascii(strip(line))


def lines_of(text: Column) -> Column:
    """Lines of a text split at \\n; null and '' give one empty line."""
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _hashes(key: Column) -> list[Column]:
    return [F.xxhash64(key).alias("h1"), F.xxhash64(F.lit("second"), key).alias("h2")]


class LineRuns:
    """The state: runs by level. ``threshold`` is the number of documents that makes a line frequent."""

    def __init__(self, threshold: int = 10, fanout: int = 4):
        if threshold < 1 or fanout < 2:
            raise ValueError("threshold must be 1 or more and fanout 2 or more")
        self.threshold, self.fanout = threshold, fanout
        self.levels: list[list[DataFrame]] = []

    def counts(self) -> DataFrame | None:
        """Documents per key over all runs."""
        runs = [run for level in self.levels for run in level]
        if not runs:
            return None
        return self._summed(runs) if len(runs) > 1 else runs[0]

    def settled(self) -> DataFrame | None:
        """Keys that have reached the threshold, with the documents counted so far."""
        found = self.counts()
        return None if found is None else found.where(F.col("n_docs") >= self.threshold)

    def frequent(self) -> DataFrame | None:
        """Keys that have reached the threshold."""
        found = self.settled()
        return None if found is None else found.select(*KEY)

    def add(self, doc_keys: DataFrame) -> None:
        """Adds a batch: one row (h1, h2) for each distinct line key of each of its documents."""
        fresh = doc_keys.groupBy(*KEY).agg(F.count(F.lit(1)).alias("n_docs"))
        settled = self.frequent()
        if settled is not None:
            fresh = fresh.join(settled, KEY, "left_anti")
        self._push(0, stored(fresh.sortWithinPartitions(*KEY)))

    def _push(self, level: int, run: DataFrame) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(run)
        if len(self.levels[level]) == self.fanout:
            merged = stored(self._summed(self.levels[level]).sortWithinPartitions(*KEY))
            self.levels[level] = []
            self._push(level + 1, merged)

    @staticmethod
    def _summed(runs: list[DataFrame]) -> DataFrame:
        return reduce(DataFrame.unionByName, runs).groupBy(*KEY).agg(F.sum("n_docs").alias("n_docs"))


def document_keys(df: DataFrame, row_col: str, text_col: str, min_chars: int = 1) -> DataFrame:
    """(row, h1, h2) for each distinct line key of at least ``min_chars`` code points of each row."""
    keys = F.array_distinct(F.transform(lines_of(F.col(text_col)), line_key))
    return (
        df.select(F.col(row_col).alias("row"), F.explode(keys).alias("key"))
        .where(F.length("key") >= min_chars)
        .select("row", *_hashes(F.col("key")))
    )


def holders(keys: DataFrame, settled: DataFrame, batches: int) -> DataFrame:
    """Rows of ``keys`` (row, h1, h2) with a key of ``settled`` (h1, h2, n_docs).

    A key is hot if its count, which ends with the batch that settles it, is more than one in
    ``HOT_SHARE`` of the rows of a batch. Counts sum to the rows at most, so there are fewer than
    ``HOT_SHARE * batches`` hot keys.
    """
    hot = F.broadcast(stored(settled.where(F.col("n_docs") * HOT_SHARE * batches > keys.count()).select(*KEY)))
    common = keys.join(hot, KEY, "left_semi")
    return common.unionByName(keys.join(hot, KEY, "left_anti").join(settled.select(*KEY), KEY, "left_semi"))


def dedup_lines(
    df: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    threshold: int = 10,
    min_chars: int = 1,
    batches: int = 3,
    fanout: int = 2,
) -> DataFrame:
    """Drops every line whose key is found in ``threshold`` documents or more.

    Returns ``df`` with ``text_col`` replaced and ``n_lines`` and ``n_dropped`` added. Null
    and empty texts count as one empty line and come back as ''. Every row counts as one
    document, repeated rows and repeated or null ids too; what an id brings to the join is only
    a set of lines that are dropped everywhere, so rows that share an id, or its hash, cannot
    harm each other. An empty table gives an empty result; columns of ``df`` named like a
    result are replaced, all others pass through. Documents are added to the runs in
    ``batches`` slices; with the defaults the first two runs are compacted before the third batch is held against them.
    """
    row = F.xxhash64(F.col(f"`{id_col}`"))
    keys = stored(document_keys(df.select(row.alias("row"), F.col(f"`{text_col}`").alias("text")), "row", "text", min_chars))
    runs = LineRuns(threshold, fanout)
    for batch in range(batches):
        part = keys if batches == 1 else keys.where(F.pmod(F.col("row"), F.lit(batches)) == batch)
        runs.add(part.select(*KEY))
    hits = holders(keys, stored(runs.settled()), batches)
    plain = [c for c in df.columns if c.lower() not in ("n_lines", "n_dropped")]
    held_row, held_drop, held_kept = unused(df, "row", "drop", "kept")
    drops = hits.groupBy(F.col("row").alias(held_row)).agg(F.collect_set(F.struct(*KEY)).alias(held_drop))
    joined = df.select(*(F.col(f"`{c}`") for c in plain)).withColumn(held_row, row).join(drops, held_row, "left")
    lines, drop = lines_of(F.col(f"`{text_col}`")), F.col(held_drop)
    first = F.transform(drop, lambda x: x["h1"])

    def stays(line: Column) -> Column:
        key = line_key(line)
        h1, h2 = _hashes(key)
        return (F.length(key) < min_chars) | ~(F.array_contains(first, h1) & F.array_contains(drop, F.struct(h1, h2)))

    kept = F.when(drop.isNull(), lines).otherwise(F.filter(lines, stays))
    cut = joined.withColumn(held_kept, kept).withColumn("n_lines", F.size(lines).cast("long"))
    cut = cut.withColumn("n_dropped", F.col("n_lines") - F.size(held_kept))
    cut = cut.withColumn(text_col, F.array_join(held_kept, "\n"))
    return cut.select(*(F.col(f"`{c}`") for c in plain), "n_lines", "n_dropped")


def digest(cut: DataFrame) -> DataFrame:
    """The contract's columns."""
    return cut.select("doc_id", "n_lines", "n_dropped", sha256_hex(F.col("text")).alias("kept_sha256"))
