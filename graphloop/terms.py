"""Node identifiers: a class tag above 48 bits of key, reversible in Spark and in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SHIFT = 48
CLASSES = [
    "region", "nation", "customer", "supplier", "part", "order", "line", "user", "event", "document", "vector", "page", "path",
    "item", "conversation", "turn", "brand", "group",
]
TAGS = {name: k + 1 for k, name in enumerate(CLASSES)}


def node_id(kind: str, key: Column) -> Column:
    """The identifier of the node of class ``kind`` with an integer key."""
    return F.lit(TAGS[kind] << SHIFT).cast("long") + key.cast("long")


def sql_id(kind: str, key: str) -> str:
    """The same as SQL text."""
    return f"({TAGS[kind] << SHIFT}::BIGINT + {key})"


def class_of(node: Column) -> Column:
    """Name of a node's class."""
    names = F.array(*(F.lit(c) for c in CLASSES))
    return F.get(names, F.shiftright(node, SHIFT).cast("int") - 1)


def key_of(node: Column) -> Column:
    """The key within the class."""
    return node.bitwiseAND(F.lit((1 << SHIFT) - 1))


def iri(node: Column) -> Column:
    """Text form of a node, such as <nation/5>."""
    return F.concat(F.lit("<"), class_of(node), F.lit("/"), key_of(node).cast("string"), F.lit(">"))
