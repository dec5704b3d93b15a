"""Quality classifier: perplexity under an interpolated modified Kneser-Ney character model.

The n-grams of all trusted text are counted where they lie and summed by key; the continuation
counts of lower orders are counts of distinct higher n-grams, and each order's probabilities
come from a join with the next lower order, sharded by language and n-gram. A model of every
language and one of all languages together ("*") share the tables. Documents are scored by
the highest order that knows an n-gram, with the usual back-off weights below it, and judged
by trusted documents that the model has not seen: how far these lie above the median of their
language, for their length, sets how far others may.

Scoring looks n-grams up in a broadcast copy of the tables where these have at most
``BROADCAST_ROWS`` rows, which is checked; beyond that it joins the n-gram counts of documents with them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphloop.materialize import release, stored

ORDER = 4
BITS = 15
POOLED = "*"
BROADCAST_ROWS = 4_000_000
CHUNK = 1_000_000
STEADY = 400
_ALPHABET = 2**BITS


def grams(text: str, order: int = ORDER) -> np.ndarray:
    """Codes of the n-grams that end at each character and at the end of the text.

    A character is one of ``2**BITS - 1`` classes, its code point modulo their number: no two characters that
    lie less than that apart share a class, so none of one script do. Class 0 pads the start and marks the end.
    """
    cps = np.frombuffer(text.encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
    padded = np.zeros(len(cps) + order, dtype=np.int64)
    padded[order - 1 : -1] = (cps + (_ALPHABET - 2)) % (_ALPHABET - 1) + 1
    code = np.zeros(len(cps) + 1, dtype=np.int64)
    for k in range(order):
        code = (code << BITS) | padded[k : k + len(cps) + 1]
    return code


def count_grams(trusted: DataFrame, order: int = ORDER) -> DataFrame:
    """(lang, code, n) over rows (lang, text), with the pooled language."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list[np.ndarray]] = {}
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            for lang, codes in held.items():
                code, n = np.unique(np.concatenate(codes), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(code)), pa.array(code), pa.array(n)], names=["lang", "code", "n"])

        for batch in batches:
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist(), strict=True):
                held.setdefault(lang if lang is not None else POOLED, []).append(grams(text, order))
                size += len(text)
                if size >= CHUNK:
                    yield from flush()
                    held, size = {}, 0
        yield from flush()

    counted = trusted.select("lang", "text").mapInArrow(run, "lang string, code long, n long")
    counted = counted.groupBy("lang", "code").agg(F.sum("n").alias("n"))
    both = F.explode(F.array_distinct(F.array("lang", F.lit(POOLED)))).alias("lang")
    return counted.select(both, "code", "n").groupBy("lang", "code").agg(F.sum("n").alias("n"))


def _mask(code: Column, order: int) -> Column:
    return code.bitwiseAND(F.lit(2 ** (BITS * order) - 1))


def _discounts(counts: DataFrame) -> DataFrame:
    """(lang, d1, d2, d3) from counts of counts."""
    few = [F.sum(F.when(F.col("n") == k, 1).otherwise(0)).cast("double").alias(f"n{k}") for k in (1, 2, 3, 4)]
    y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))
    known = (F.col("n1") > 0) & (F.col("n2") > 0)

    def discount(k: int) -> Column:
        exact = F.lit(float(k)) - (k + 1) * F.when(known, y) * F.try_divide(F.col(f"n{k + 1}"), F.col(f"n{k}"))
        return F.greatest(F.lit(0.1 * k), F.least(F.coalesce(exact, F.lit(0.5 * k)), F.lit(0.95 * k))).alias(f"d{k}")

    return counts.groupBy("lang").agg(*few).select("lang", *(discount(k) for k in (1, 2, 3)))


def probabilities(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """(lang, kind, code, value): kind k > 0 has log probabilities of k-grams, -k log back-off weights of their contexts."""
    levels = {order: counts}
    for k in range(order - 1, 0, -1):
        levels[k] = levels[k + 1].groupBy("lang", _mask(F.col("code"), k).alias("code")).agg(F.count(F.lit(1)).alias("n"))
    out, lower = None, None
    for k in range(1, order + 1):
        rows = levels[k].join(F.broadcast(_discounts(levels[k])), "lang")
        rows = rows.withColumn("d", F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3")))
        rows = rows.withColumn("context", F.shiftright("code", BITS))
        contexts = rows.groupBy("lang", "context").agg(F.sum("n").alias("total"), F.sum("d").alias("mass"))
        rows = rows.join(contexts, ["lang", "context"])
        if lower is None:
            below = F.lit(1.0 / _ALPHABET)
        else:
            rows = rows.withColumn("suffix", _mask(F.col("code"), k - 1))
            rows = rows.join(lower.select("lang", F.col("code").alias("suffix"), F.col("p").alias("below")), ["lang", "suffix"])
            below = F.col("below")
        p = (F.col("n") - F.col("d")) / F.col("total") + F.col("mass") / F.col("total") * below
        lower = stored(rows.select("lang", "code", p.alias("p")))
        logs = lower.select("lang", F.lit(k).alias("kind"), "code", F.log("p").alias("value"))
        weights = contexts.select("lang", F.lit(-k).alias("kind"), F.col("context").alias("code"), F.log(F.col("mass") / F.col("total")).alias("value"))
        both = logs.unionByName(weights)
        out = both if out is None else out.unionByName(both)
    return out


class Lookup:
    """The tables of one language as sorted arrays."""

    def __init__(self, tables: dict[int, tuple[np.ndarray, np.ndarray]], order: int):
        self.tables, self.order = tables, order

    def _find(self, kind: int, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        keys, values = self.tables.get(kind, (np.empty(0, np.int64), np.empty(0)))
        if not len(keys):
            return np.zeros(len(codes), dtype=bool), np.zeros(len(codes))
        at = np.minimum(np.searchsorted(keys, codes), len(keys) - 1)
        return keys[at] == codes, values[at]

    def score(self, codes: np.ndarray) -> np.ndarray:
        """Log probability of each n-gram."""
        out = np.zeros(len(codes))
        open_rows = np.arange(len(codes))
        for k in range(self.order, 0, -1):
            part = codes[open_rows] & (2 ** (BITS * k) - 1)
            hit, value = self._find(k, part)
            out[open_rows[hit]] += value[hit]
            open_rows, part = open_rows[~hit], part[~hit]
            if not len(open_rows):
                return out
            seen, weight = self._find(-k, part >> BITS)
            out[open_rows[seen]] += weight[seen]
        out[open_rows] -= np.log(_ALPHABET)
        return out


def _score_by_lookup(rows: DataFrame, model: DataFrame, order: int) -> DataFrame:
    table = model.toArrow()
    lang = table.column("lang").combine_chunks().dictionary_encode()
    names, lang = lang.dictionary.to_pylist(), lang.indices.to_numpy()
    kind, code, value = (table.column(c).to_numpy() for c in ("kind", "code", "value"))
    del table
    by = np.lexsort((code, kind, lang))
    lang, kind, code, value = lang[by], kind[by], code[by], value[by]
    cuts = np.flatnonzero((np.diff(lang) != 0) | (np.diff(kind) != 0)) + 1
    parts: dict[str, dict] = {}
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(lang)], strict=True):
        if b > a:
            parts.setdefault(names[lang[a]], {})[int(kind[a])] = (code[a:b], value[a:b])
    tables = {name: Lookup(own, order) for name, own in parts.items()}
    held = rows.sparkSession.sparkContext.broadcast(tables)

    base = rows.select("text", "lang", "id", "n_grams")
    schema = T.StructType([*base.schema.fields[1:], T.StructField("log_p", T.DoubleType())])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                sums = []
                for text, name in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    table = held.value.get(name) or held.value.get(POOLED)
                    sums.append(float(table.score(grams(text, order)).sum()) if text and table else None)
                yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(sums, pa.float64())], names=schema.names)

    return base.mapInArrow(score, schema)


def _score_by_join(rows: DataFrame, model: DataFrame, order: int) -> DataFrame:
    """The same sums by joins of each row's n-gram counts with the tables."""
    numbered = stored(rows.withColumn("_row", F.monotonically_increasing_id()))
    known = model.select("lang").distinct()
    asked = numbered.where(F.length("text") > 0).select("_row", "lang", "text").join(known.withColumn("_known", F.lit(True)), "lang", "left")
    asked = asked.withColumn("lang", F.when(F.col("_known"), F.col("lang")).otherwise(F.lit(POOLED)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, lang, text in zip(*(batch.column(c).to_pylist() for c in ("_row", "lang", "text")), strict=True):
                code, n = np.unique(grams(text, order), return_counts=True)
                arrays = [pa.array(np.full(len(code), row)), pa.array([lang] * len(code)), pa.array(code), pa.array(n)]
                yield pa.RecordBatch.from_arrays(arrays, names=["_row", "lang", "code", "n"])

    counts = asked.select("_row", "lang", "text").mapInArrow(run, "_row long, lang string, code long, n long")
    value = F.lit(-float(np.log(_ALPHABET)))
    for k in range(1, order + 1):
        logs = model.where(F.col("kind") == k).select("lang", F.col("code").alias(f"c{k}"), F.col("value").alias(f"p{k}"))
        weights = model.where(F.col("kind") == -k).select("lang", F.col("code").alias(f"x{k}"), F.col("value").alias(f"w{k}"))
        counts = counts.withColumn(f"c{k}", _mask(F.col("code"), k)).withColumn(f"x{k}", F.shiftright(_mask(F.col("code"), k), BITS))
        counts = counts.join(logs, ["lang", f"c{k}"], "left").join(weights, ["lang", f"x{k}"], "left")
        value = F.coalesce(F.col(f"p{k}"), F.coalesce(F.col(f"w{k}"), F.lit(0.0)) + value)
    sums = counts.groupBy("_row").agg(F.sum(F.col("n") * value).alias("log_p"))
    return numbered.join(sums, "_row", "left").drop("_row")


def _looseness() -> Column:
    """How much wider than in long texts perplexities of the row's length scatter."""
    return F.sqrt(1 + STEADY / F.col("n_grams"))


def _limits(judged: DataFrame, quantile: float) -> tuple[DataFrame, DataFrame]:
    """(own, middle) by language and pooled, and one row (spread), from rows (lang, n_grams, perplexity).

    ``middle`` is the median logarithm. ``spread`` is the ``quantile`` over all languages of the
    distance from it, divided by what is usual at the length: a language with few rows has no
    tail of its own, and a short text that is odd by chance does not widen the limit of long ones.
    Where rows are so few that the quantile is their maximum, twice the second largest is the most.
    """
    rows = judged.select(F.coalesce("lang", F.lit(POOLED)).alias("lang"), "n_grams", F.log("perplexity").alias("x"))
    own = F.explode(F.array_distinct(F.array("lang", F.lit(POOLED)))).alias("own")
    middles = rows.select(own, "x").groupBy("own").agg(F.percentile_approx("x", 0.5, 10_000).alias("middle"))
    apart = rows.join(F.broadcast(middles), rows["lang"] == middles["own"])
    apart = stored(apart.select(((F.col("x") - F.col("middle")) / _looseness()).alias("u")))
    second = apart.orderBy(F.desc("u")).limit(2).agg(F.min("u").alias("second"))
    tail = apart.agg(F.percentile_approx("u", quantile, 10_000).alias("tail"))
    return middles, tail.crossJoin(second).select(F.least("tail", F.when(F.col("second") > 0, 2 * F.col("second"))).alias("spread"))


def classify(
    df: DataFrame,
    trusted_ids: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    lang_col: str = "lang",
    quantile: float = 0.99,
    folds: int = 5,
    order: int = ORDER,
    broadcast_rows: int = BROADCAST_ROWS,
) -> DataFrame:
    """(id, lang, n_grams, perplexity, threshold, kept) of every row.

    ``trusted_ids`` has the ids of trusted rows in a column ``id``; one in ``folds``, by a hash
    of the id, is kept from the model and sets the thresholds (``_limits``), by language and
    length. Perplexity is per character
    with the end of the text; null and empty texts have none and are not kept. A null language,
    or one without trusted text, is judged by the pooled model and median. Without
    any trusted text there is no perplexity, and every text that is not empty is kept. Rows are
    judged one by one, repeats too; an empty table gives an empty result.
    """
    spark = df.sparkSession
    base = df.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    trusted_ids = trusted_ids.select("id").where("id is not null").distinct()
    unseen = F.pmod(F.xxhash64(F.lit("fold"), "id"), F.lit(folds)) == 0
    # Ids grow with the corpus, so they are never broadcast: the same plan at every size.
    trusted = base.join(trusted_ids.where(~unseen).hint("merge"), "id", "left_semi").where(F.length("text") > 0)
    counts = stored(count_grams(trusted, order))
    release(spark)
    model = stored(probabilities(counts, order))
    release(spark)
    score = _score_by_lookup if model.count() <= broadcast_rows else _score_by_join
    rows = base.withColumn("n_grams", F.coalesce(F.length("text"), F.lit(0)).cast("long") + 1)
    scored = score(rows, model, order).select("id", "lang", "n_grams", F.exp(-F.col("log_p") / F.col("n_grams")).alias("perplexity"))
    scored = stored(scored)
    judged = scored.join(trusted_ids.where(unseen), "id", "left_semi").where(F.col("perplexity").isNotNull())
    middles, spread = _limits(judged, quantile)
    pooled = middles.where(F.col("own") == POOLED).select(F.col("middle").alias("pooled"))
    out = scored.join(F.broadcast(middles), scored["lang"] == middles["own"], "left").join(F.broadcast(pooled.crossJoin(spread)), F.lit(True), "left")
    # The last digits of the logarithm must not reject the row that sets the limit.
    limit = F.exp(F.coalesce("middle", "pooled") + F.col("spread") * _looseness()) * (1 + 1e-9)
    out = out.withColumn("threshold", limit)
    kept = (F.col("n_grams") > 1) & F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(True))
    return out.select("id", "lang", "n_grams", "perplexity", "threshold", kept.alias("kept"))


def digest(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Judges documents by those that are labelled of good quality and not toxic."""
    trusted = labels.where("quality = 1 and toxic = 0").select(F.col("doc_id").alias("id"))
    return classify(documents, trusted).withColumnRenamed("id", "doc_id")
