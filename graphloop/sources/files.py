"""Triple dumps, edge lists and result files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_ntriples(triples: DataFrame, path: str) -> None:
    """(s, p, o) as text, one statement a line; subjects and predicates are IRIs, objects escaped strings."""
    escaped = F.regexp_replace(F.regexp_replace(F.regexp_replace("o", r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n")
    line = F.concat(F.lit("<"), F.col("s"), F.lit("> <"), F.col("p"), F.lit('> "'), escaped, F.lit('" .'))
    triples.select(line.alias("value")).write.text(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o) of a triple dump; objects are IRIs or strings, whose type or language is dropped. Other lines are skipped."""
    pattern = r'^<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.\s*$'
    lines = spark.read.text(path).where(F.col("value").rlike(pattern))
    part = lambda k: F.regexp_extract("value", pattern, k)
    text = F.regexp_replace(F.regexp_replace(F.regexp_replace(part(4), r"\\n", "\n"), r'\\"', '"'), r"\\\\", r"\\")
    return lines.select(part(1).alias("s"), part(2).alias("p"), F.when(part(3) != "", part(3)).otherwise(text).alias("o"))


def write_edges(edges: DataFrame, path: str) -> None:
    """Space-separated src dst [weight]."""
    columns = [c for c in ("src", "dst", "weight") if c in edges.columns]
    edges.select(*columns).write.csv(path, sep=" ")


def read_edges(spark: SparkSession, path: str, weighted: bool = False) -> DataFrame:
    return spark.read.csv(path, sep=" ", schema="src long, dst long" + (", weight double" if weighted else ""))


def write_bucketed(edges: DataFrame, table: str, buckets: int, by: str = "src") -> None:
    """A table laid out by one end, so that joins on it need no shuffle."""
    edges.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").saveAsTable(table)


def result_json(df: DataFrame) -> DataFrame:
    """(value): one JSON object per solution, unbound variables left out."""
    return df.select(F.to_json(F.struct(*(F.col(f"`{c}`") for c in df.columns))).alias("value"))
