"""A corpus pipeline of five of the text operators, from documents to token ids.

``STAGES`` lists (name, function); every function takes (spark, docs, sf_dir), works on all
its predecessor kept and returns a DataFrame, which is written as Parquet and read again as
the next one's ``docs``. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloop.llm import byte_bpe, line_dedup, mixing, near_dup, quality_rules
from graphloop.materialize import stored

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
VOCABULARY = "byte_bpe_multi_50k.tiktoken"

# Near duplicates and mixing are not exact in SQL at any useful speed; tests/llm/test_pipeline.py
# holds the rows of run() against a plain Python version instead.
ORACLE_SQL = None


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that fail a quality rule."""
    judged = quality_rules.ledger(docs.select(COLUMNS))
    return judged.where(quality_rules.passes(quality_rules.STRICT)).select(COLUMNS)


def drop_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes out lines that ten documents or more share."""
    cut = line_dedup.dedup_lines(docs.select(COLUMNS))
    return cut.withColumn("n_chars", F.length("text").cast("long")).select(COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near duplicates: five words, similarity 0.8."""
    kept = near_dup.near_duplicates(docs).where("kept").select(F.col("id").alias("_kept")).distinct()
    return docs.select(COLUMNS).join(kept, F.col("doc_id").eqNullSafe(F.col("_kept")), "left_semi")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mixes sources to their targets; a document taken several times becomes several rows.

    Rows with one id are taken as often as the one of them that is taken most.
    """
    copies = mixing.mix(docs).where("copies > 0").groupBy(F.col("id").alias("_id")).agg(F.max("copies").alias("_copies"))
    taken = docs.select(COLUMNS).join(copies, F.col("doc_id").eqNullSafe(F.col("_id")))
    return taken.withColumn("_turn", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_copies")))).select(COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, and whether they decode to its text."""
    coded = byte_bpe.encode_texts(docs.select(COLUMNS), public_tokenizers.path(VOCABULARY), with_offsets=False, with_decoded=True)
    round_trip = F.col("decoded") == F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return coded.select("doc_id", "lang", "source", F.size("ids").cast("long").alias("n_tokens"), "ids", round_trip.alias("round_trip"))


STAGES = [
    ("quality_rules", keep_good),
    ("line_dedup", drop_common_lines),
    ("near_dedup", drop_near_duplicates),
    ("mix_sources", mix_sources),
    ("byte_bpe", encode),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    *first, (_, last) = STAGES
    for _, stage in first:
        docs = stored(stage(spark, docs, sf_dir))
    return last(spark, docs, sf_dir)
