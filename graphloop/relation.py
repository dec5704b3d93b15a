"""Solution sequences: a DataFrame with the variables that some solutions leave unbound."""

from __future__ import annotations

from dataclasses import dataclass
from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class TooLarge(ValueError):
    """What is asked for would need more than can be held or made; nothing was dropped to make it fit."""


@dataclass(frozen=True)
class Relation:
    """``df`` has one column per variable; only variables in ``maybe`` may be null. ``kept`` marks snapshots; ``files`` are those it reads."""

    df: DataFrame
    maybe: frozenset = frozenset()
    rows: int | None = None
    kept: bool = False
    files: frozenset = frozenset()

    @property
    def vars(self) -> list[str]:
        return self.df.columns

    @classmethod
    def of(cls, df: DataFrame, certain: bool = False) -> Relation:
        """Columns that the schema lets be null count as possibly unbound, unless ``certain``."""
        return cls(df, frozenset() if certain else frozenset(f.name for f in df.schema if f.nullable))


@dataclass(frozen=True)
class Fingerprint:
    """Identifies a set of solutions up to hash collisions of about 2**-128."""

    count: int
    total: Decimal
    xor: int


def _canonical(df: DataFrame) -> list[Column]:
    out = []
    for name, kind in sorted(df.dtypes):
        c = F.col(f"`{name}`")
        if kind in ("double", "float"):
            c = F.when(F.isnan(c), F.lit(float("nan"))).when(c == 0, F.lit(0.0)).otherwise(c).cast("double")
        elif kind in ("int", "smallint", "tinyint"):
            c = c.cast("long")
        out.append(F.struct(F.lit(name), c.isNull(), c))
    return out


def fingerprint(df: DataFrame) -> Fingerprint:
    """Of the set of solutions: row order and duplicates do not matter. Runs a job."""
    columns = _canonical(df)
    if not columns:
        return Fingerprint(int(not df.isEmpty()), Decimal(0), 0)
    hashed = df.select(F.xxhash64(F.lit(1), *columns).alias("a"), F.xxhash64(F.lit(2), *columns).alias("b")).distinct()
    row = hashed.agg(F.count(F.lit(1)), F.sum(F.col("a").cast("decimal(38,0)")), F.bit_xor("b")).first()
    return Fingerprint(row[0], row[1] or Decimal(0), row[2] or 0)


def same_set(a: DataFrame, b: DataFrame) -> bool:
    """Exact equality of two sets of solutions, unbound being equal to unbound. Runs a job."""
    if sorted(a.columns) != sorted(b.columns):
        return a.isEmpty() and b.isEmpty()
    marked = a.distinct().withColumn("_side", F.lit(1)).unionByName(b.distinct().withColumn("_side", F.lit(2)))
    lone = marked.groupBy(*(F.col(f"`{c}`") for c in a.columns)).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") < 2)
    return lone.isEmpty()
