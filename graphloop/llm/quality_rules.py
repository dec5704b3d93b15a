"""Quality rules as a ledger: measure once, keep one failure bit per rule, judge by policies.

``measure`` computes the measurements of every text in one pass; ``ledger`` evaluates each
rule once on them and stores the failures as bits beside the measurements. A policy is a
named, versioned set of rules, that is, a mask; applying one, or comparing several, or asking
what a rule removes that no other rule does, needs only bitwise arithmetic on the ledger.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.llm.text import SPACES, unused

WINDOW = 8
# The characters that count as symbols.
SYMBOLS = "#*$%&|<>"

MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_letters", "n_upper", "n_exclaim", "n_adjacent"]


@dataclass(frozen=True)
class Rule:
    """``fails`` is a SQL condition on the measurements; ``bit`` is fixed for good."""

    bit: int
    name: str
    fails: str


@dataclass(frozen=True)
class Policy:
    name: str
    version: int
    rules: tuple[str, ...]


RULES = [
    Rule(0, "few_words", "n_words < 20"),
    Rule(1, "repeated_words", "100 * n_repeat_words > 30 * n_words"),
    Rule(2, "symbols", "100 * n_symbols > 10 * n_words"),
    Rule(3, "shouting", "100 * n_upper > 30 * n_letters"),
    Rule(4, "exclaiming", "100 * n_exclaim > 20 * n_words"),
    Rule(5, "repeated_lines", "100 * n_dup_lines > 30 * n_lines"),
    Rule(6, "stuttering", "100 * n_adjacent > 20 * n_words"),
    Rule(7, "word_length", "word_chars < 2 * n_words OR word_chars > 20 * n_words"),
    Rule(8, "few_letters", "10 * n_letters < 6 * word_chars"),
]
BASE = Policy("base", 1, ("few_words", "repeated_words"))
STRICT = Policy("strict", 1, tuple(r.name for r in RULES))
POLICIES = [BASE, STRICT]

_CLASSES: np.ndarray | None = None
_SPACE, _SYMBOL, _UPPER, _LETTER, _EXCLAIM = 1, 2, 3, 4, 5


def _classes() -> np.ndarray:
    global _CLASSES
    if _CLASSES is None:
        table = np.zeros(0x110000, dtype=np.uint8)
        for cp in range(0x110000):
            c = chr(cp)
            if c.isalpha():
                table[cp] = _UPPER if c.isupper() else _LETTER
        for chars, kind in ((SPACES, _SPACE), (SYMBOLS, _SYMBOL), ("!", _EXCLAIM)):
            table[[ord(c) for c in chars]] = kind
        _CLASSES = table
    return _CLASSES


def repeated_words(ids: np.ndarray) -> int:
    """Positions covered by windows of ``WINDOW`` words that occur twice or more."""
    n = len(ids) - WINDOW + 1
    if n < 2:
        return 0
    mixed = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    mixed ^= mixed >> np.uint64(29)
    key = np.zeros(n, dtype=np.uint64)
    for k in range(WINDOW):
        key = key * np.uint64(0xBF58476D1CE4E5B9) + mixed[k : k + n]
    order = np.argsort(key, kind="stable")
    at = np.flatnonzero(key[order[1:]] == key[order[:-1]])
    if not len(at):
        return 0
    left, right = order[at], order[at + 1]
    same = np.ones(len(at), dtype=bool)
    for k in range(WINDOW):  # equal keys are confirmed word by word
        same &= ids[left + k] == ids[right + k]
    edges = np.zeros(len(ids) + 1, dtype=np.int64)
    starts = np.unique(np.concatenate([left[same], right[same]]))
    edges[starts] += 1
    edges[starts + WINDOW] -= 1
    return int((np.cumsum(edges[:-1]) > 0).sum())


def measure_text(text: str | None) -> tuple[int, ...]:
    """The values of ``MEASURES`` for one text."""
    if not text:
        return (0,) * len(MEASURES)
    kinds = np.bincount(_classes()[np.frombuffer(text.encode("utf-32-le"), dtype=np.uint32)], minlength=6)
    words = text.encode().split()  # splits bytes at exactly the six separators
    known: dict[bytes, int] = {}
    ids = np.fromiter((known.setdefault(w, len(known)) for w in words), dtype=np.int64, count=len(words))
    lines = [line for line in text.split("\n") if line.strip(SPACES)]
    return (
        len(words),
        len(text) - int(kinds[_SPACE]),
        int(kinds[_SYMBOL]),
        len(lines) - len(set(lines)),
        repeated_words(ids),
        len(lines),
        int(kinds[_UPPER] + kinds[_LETTER]),
        int(kinds[_UPPER]),
        int(kinds[_EXCLAIM]),
        int((ids[1:] == ids[:-1]).sum()),
    )


def ledger(df: DataFrame, text_col: str = "text", rules: list[Rule] = RULES) -> DataFrame:
    """Adds the measurements and ``failed`` (bits of the rules that fail) to ``df``.

    Null and empty texts have no words, lines or letters. Each row is judged by itself, whole;
    repeats and ties get equal results, an empty table stays empty, and columns of ``df``
    named like a result are replaced.
    """
    if len({r.bit for r in rules}) < len(rules) or any(not 0 <= r.bit < 63 for r in rules):
        raise ValueError("rules need bits of their own between 0 and 62")

    @F.pandas_udf(", ".join(f"{m} long" for m in MEASURES))
    def measure(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([measure_text(t) for t in texts], columns=MEASURES)

    kept = [c for c in df.columns if c.lower() not in (*MEASURES, "failed")]
    (found,) = unused(df, "measured")
    measured = df.withColumn(found, measure(F.col(f"`{text_col}`"))).select(*(F.col(f"`{c}`") for c in kept), *(F.col(f"`{found}`.{m}").alias(m) for m in MEASURES))
    failed = F.lit(0).cast("long")
    for rule in rules:
        failed = failed.bitwiseOR(F.when(F.expr(rule.fails), F.lit(1 << rule.bit)).otherwise(F.lit(0)).cast("long"))
    return measured.withColumn("failed", failed)


def mask(policy: Policy, rules: list[Rule] = RULES) -> int:
    """The bits of a policy's rules."""
    bits = {r.name: r.bit for r in rules}
    return sum(1 << bits[name] for name in policy.rules)


def passes(policy: Policy, rules: list[Rule] = RULES):
    """Column: no rule of the policy fails."""
    return F.col("failed").bitwiseAND(F.lit(mask(policy, rules)).cast("long")) == 0


def ablation(judged: DataFrame, policies: list[Policy] = POLICIES, rules: list[Rule] = RULES) -> DataFrame:
    """(policy, version, rule, n_docs, n_kept, n_failed, n_only) for each rule of each policy.

    ``n_only`` is what the policy would keep without the rule. The ledger is first reduced to
    counts by failure bits, at most one row for each combination that occurs.
    """
    spark = judged.sparkSession
    combos = judged.groupBy("failed").agg(F.count(F.lit(1)).alias("n"))
    bits = {r.name: r.bit for r in rules}
    rows = [(p.name, p.version, mask(p, rules), name, 1 << bits[name]) for p in policies for name in p.rules]
    asked = spark.createDataFrame(rows, "policy string, version int, mask long, rule string, bit long")
    hit = F.col("failed").bitwiseAND(F.col("mask"))

    def total(condition):
        return F.coalesce(F.sum(F.when(condition, F.col("n"))), F.lit(0)).cast("long")

    # One side is the list of policies, the other the few combinations of bits.
    return (
        asked.join(F.broadcast(combos), F.lit(True), "left")
        .groupBy("policy", "version", "rule")
        .agg(
            total(F.lit(True)).alias("n_docs"),
            total(hit == 0).alias("n_kept"),
            total(F.col("failed").bitwiseAND(F.col("bit")) != 0).alias("n_failed"),
            total(hit == F.col("bit")).alias("n_only"),
        )
    )


def digest(df: DataFrame) -> DataFrame:
    """The contract's columns for rows (doc_id, text)."""
    judged = ledger(df)
    return judged.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        (~passes(BASE)).alias("base_failed"), (passes(BASE) & passes(STRICT)).alias("kept"), "failed",
    )
