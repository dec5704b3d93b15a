"""Language identification by hierarchical discrimination.

A text becomes a unit vector of square roots of hashed letter n-gram frequencies. Linear
support vector machines first tell language families apart (one against the rest), then, within the
winning family, every two languages (one against one, most wins, then the larger sum of
margins). Training is a deterministic accelerated descent on the squared hinge loss over a
bounded sample of labelled rows: about ``per_language`` rows of each language.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.llm.text import unused

# Families of common language codes; any other code is a family of its own.
FAMILIES = {
    "germanic": ["en", "de", "nl", "sv", "da", "no", "nb", "nn", "is", "af"],
    "romance": ["fr", "es", "it", "pt", "ro", "ca", "gl", "oc"],
    "slavic": ["ru", "uk", "be", "pl", "cs", "sk", "bg", "sr", "hr", "sl", "mk", "bs"],
    "indic": ["hi", "mr", "ne", "bn", "pa", "gu"],
    "turkic": ["tr", "az", "kk", "uz", "ky", "tk"],
    "uralic": ["fi", "et", "hu"],
    "semitic": ["ar", "he", "mt", "am"],
}
_FAMILY = {code: family for family, codes in FAMILIES.items() for code in codes}
UNDETERMINED = "und"
DIMENSIONS = 2048
MAX_LANGUAGES = 1000
_LETTER = np.zeros(0x110000, dtype=bool)


def _letters() -> np.ndarray:
    if not _LETTER[ord("a")]:
        _LETTER[[cp for cp in range(0x110000) if chr(cp).isalpha()]] = True
    return _LETTER


def features(texts: list[str | None]) -> np.ndarray:
    """A row of ``DIMENSIONS`` floats per text; all zero where a text has no letter."""
    out = np.zeros((len(texts), DIMENSIONS), dtype=np.float32)
    letters = _letters()
    for i, text in enumerate(texts):
        if not text:
            continue
        cps = np.frombuffer(f" {text.lower()} ".encode("utf-32-le"), dtype=np.uint32)
        is_letter = letters[cps]
        if not is_letter.any():
            continue
        cps = np.where(is_letter, cps, 0)
        cps = cps[np.append(True, (cps[1:] != 0) | (cps[:-1] != 0))]  # runs of non-letters count as one gap
        counts = np.zeros(DIMENSIONS)
        code = np.zeros(len(cps), dtype=np.uint32)
        for order in (1, 2, 3):
            code = code[: len(cps) - order + 1] * np.uint32(0x01000193) ^ cps[order - 1 :]
            mixed = (code + np.uint32(order)) * np.uint32(0x9E3779B1)
            counts += np.bincount(mixed >> np.uint32(21), minlength=DIMENSIONS) / len(code) if len(code) else 0
        row = np.sqrt(counts)
        out[i] = row / np.linalg.norm(row)
    return out


def _fit(x: np.ndarray, y: np.ndarray, penalty: float = 1e-4, rounds: int = 300) -> np.ndarray:
    """Weights and bias of a linear machine; classes weigh the same however many rows they have."""
    x = np.hstack([x, np.ones((len(x), 1), dtype=np.float32)]).astype(np.float64)
    share = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum()))
    w = ahead = np.zeros(x.shape[1])
    step, t = 1.0 / (4.0 + penalty), 1.0
    for _ in range(rounds):
        slack = np.maximum(0.0, 1.0 - y * (x @ ahead))
        gradient = penalty * ahead - 2.0 * (x.T @ (share * y * slack))
        new = ahead - step * gradient
        t_new = (1 + (1 + 4 * t * t) ** 0.5) / 2
        ahead = new + (t - 1) / t_new * (new - w)
        w, t = new, t_new
    return w


class LanguageModel:
    """Family machines, then pairs of languages within each family."""

    def __init__(self, x: np.ndarray, languages: list[str]):
        self.languages = sorted(set(languages))
        family = {code: _FAMILY.get(code, f"only {code}") for code in self.languages}
        self.families = sorted(set(family.values()))
        labels = np.array(languages)
        own = np.array([family[code] for code in languages])
        self.members = [[self.languages.index(c) for c in self.languages if family[c] == f] for f in self.families]
        several = len(self.families) > 1
        self.top = np.array([_fit(x, np.where(own == f, 1.0, -1.0)) for f in self.families]) if several else None
        self.pairs: dict[tuple[int, int], np.ndarray] = {}
        for group in self.members:
            for a, b in combinations(group, 2):
                rows = (labels == self.languages[a]) | (labels == self.languages[b])
                self.pairs[a, b] = _fit(x[rows], np.where(labels[rows] == self.languages[a], 1.0, -1.0))

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        """(language, score between 0 and 1) of each row; rows of zeros are undetermined."""
        n = len(x)
        score = np.ones(n)
        family = np.zeros(n, dtype=np.int64)
        if self.top is not None:
            margins = x @ self.top[:, :-1].T + self.top[:, -1]
            family = margins.argmax(axis=1)
            ordered = np.sort(margins, axis=1)
            score = 1 / (1 + np.exp(-2 * (ordered[:, -1] - ordered[:, -2])))
        found = np.zeros(n, dtype=np.int64)
        for f, group in enumerate(self.members):
            rows = np.flatnonzero(family == f)
            if not len(rows):
                continue
            wins, sums = np.zeros((len(rows), len(group))), np.zeros((len(rows), len(group)))
            closest = np.full(len(rows), np.inf)
            for i, j in combinations(range(len(group)), 2):
                w = self.pairs[group[i], group[j]]
                margin = x[rows] @ w[:-1] + w[-1]
                wins[:, i] += margin >= 0
                wins[:, j] += margin < 0
                sums[:, i] += margin
                sums[:, j] -= margin
                closest = np.minimum(closest, np.abs(margin))
            best = np.lexsort((sums.T, wins.T), axis=0)[-1] if len(group) > 1 else np.zeros(len(rows), dtype=np.int64)
            found[rows] = np.array(group)[best]
            if len(group) > 1:
                score[rows] *= 1 / (1 + np.exp(-4 * closest))
        empty = ~x.any(axis=1)
        score[empty] = 0.0
        return [UNDETERMINED if e else self.languages[k] for e, k in zip(empty.tolist(), found.tolist(), strict=True)], score


def held_out(id_col: Column) -> Column:
    """Rows whose CRC-32 of the id as text leaves 1 modulo 3; a null id is not held out."""
    return F.coalesce(F.pmod(F.crc32(id_col.cast("string")), F.lit(3)) == 1, F.lit(False))


def train(labelled: DataFrame, text_col: str, lang_col: str, order: Column, per_language: int = 500) -> LanguageModel | None:
    """A model from rows with a language; ``order`` is a hash column that draws the sample.

    The driver gets about ``per_language`` feature rows of each language, however many rows
    there are, and refuses more than ``MAX_LANGUAGES`` languages.
    """
    known = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    counts = {r[0]: r[1] for r in known.groupBy(lang_col).count().take(MAX_LANGUAGES + 1)}
    if len(counts) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    if not counts:
        return None
    shares = F.create_map(*(F.lit(v) for code, n in counts.items() for v in (code, min(1.0, per_language / n))))
    drawn = F.pmod(order, F.lit(2**31)) < F.element_at(shares, F.col(lang_col)) * 2**31

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = features(batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("turn"), pa.array([row.tobytes() for row in x], pa.binary())], names=["lang", "turn", "x"])

    sample = known.where(drawn).select(F.col(lang_col).alias("lang"), order.alias("turn"), F.col(text_col).alias("text"))
    rows = sample.mapInArrow(vectors, "lang string, turn long, x binary").toPandas().sort_values(["lang", "turn", "x"])
    x = np.frombuffer(b"".join(rows["x"]), dtype=np.float32).reshape(-1, DIMENSIONS) if len(rows) else np.zeros((0, DIMENSIONS))
    usable = x.any(axis=1)
    return LanguageModel(x[usable], rows["lang"][usable].tolist()) if usable.any() else None


def identify(df: DataFrame, model: LanguageModel | None, text_col: str = "text") -> DataFrame:
    """Adds ``lang_pred`` and ``score`` to ``df``.

    Texts that are null or have no letter are ``und`` with score 0, and so is everything
    without a model. Whole texts are judged, row by row; an empty table stays empty and
    columns of ``df`` named like a result are replaced.
    """
    held = df.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("lang_pred string, score double")
    def judge(texts):
        import pandas as pd

        languages, scores = [], []
        values = texts.tolist()
        for at in range(0, len(values), 256):
            part = values[at : at + 256]
            if held.value is None:
                found, score = [UNDETERMINED] * len(part), np.zeros(len(part))
            else:
                found, score = held.value.predict(features(part))
            languages += found
            scores.append(score)
        return pd.DataFrame({"lang_pred": languages, "score": np.concatenate(scores) if scores else []})

    kept = [c for c in df.columns if c.lower() not in ("lang_pred", "score")]
    (found,) = unused(df, "judged")
    judged = df.withColumn(found, judge(F.col(f"`{text_col}`")))
    return judged.select(*(F.col(f"`{c}`") for c in kept), *(F.col(f"`{found}`.{c}").alias(c) for c in ("lang_pred", "score")))


def digest(documents: DataFrame) -> DataFrame:
    """The contract's columns for rows (doc_id, text, lang)."""
    marked = documents.select("doc_id", "text", "lang", held_out(F.col("doc_id")).alias("held_out"))
    learned = marked.where(~F.col("held_out") & F.col("doc_id").isNotNull())
    model = train(learned, "text", "lang", F.xxhash64(F.lit("sample"), "doc_id"))
    return identify(marked.select("doc_id", "held_out", "text"), model).select("doc_id", "held_out", "lang_pred", "score")
