"""Graphs as virtual triples: each predicate is a view of one table, so constants and projections reach its scan."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloop.sources.edges import read
from graphloop.terms import node_id


@dataclass(frozen=True)
class Predicate:
    """Subject and object expressions over a table; ``only`` restricts its rows."""

    table: Callable[[], DataFrame]
    subject: Column
    object: Column
    only: Column | None = None
    source: str = ""

    def pairs(self) -> DataFrame:
        df = self.table()
        if self.only is not None:
            df = df.where(self.only)
        return df.select(self.subject.alias("s"), self.object.alias("o"))


@dataclass
class Catalog:
    """Predicates by name; ``graphs`` are the other graphs of the dataset."""

    spark: SparkSession
    predicates: dict[str, Predicate] = field(default_factory=dict)
    graphs: dict[str, Catalog] = field(default_factory=dict)

    def add(self, name: str, df: DataFrame | Callable[[], DataFrame], s: str = "s", o: str = "o") -> Catalog:
        """Registers two columns of a DataFrame as a predicate."""
        table = df if callable(df) else (lambda: df)
        self.predicates[name] = Predicate(table, F.col(s), F.col(o))
        return self

    def pairs(self, name: str) -> DataFrame:
        if name not in self.predicates:
            raise KeyError(f"unknown predicate {name!r}")
        return self.predicates[name].pairs()

    def triples(self, names=None) -> DataFrame:
        """(s, p, o) of all predicates, or of some; objects as text."""
        parts = [
            self.pairs(n).where(F.col("s").isNotNull() & F.col("o").isNotNull()).select(F.col("s").cast("string"), F.lit(n).alias("p"), F.col("o").cast("string"))
            for n in (self.predicates if names is None else names)
        ]
        return reduce(DataFrame.union, parts) if parts else self.spark.createDataFrame([], "s string, p string, o string")

    def nodes(self) -> DataFrame:
        """All subjects and objects, as text: the active domain."""
        t = self.triples()
        return t.select(F.col("s").alias("value")).union(t.select("o")).distinct()


def tables_catalog(spark: SparkSession, sf_dir: str) -> Catalog:
    """Keys and attributes of the given tables as predicates."""

    def t(name):
        return lambda: read(spark, sf_dir, name)

    c = F.col
    order, customer, nation = node_id("order", c("o_orderkey")), node_id("customer", c("c_custkey")), node_id("nation", c("n_nationkey"))
    supplier, part = node_id("supplier", c("s_suppkey")), node_id("part", c("p_partkey"))
    line_order = node_id("order", c("l_orderkey"))
    p = {
        "region_name": ("region", node_id("region", c("r_regionkey")), c("r_name")),
        "nation_name": ("nation", nation, c("n_name")),
        "in_region": ("nation", nation, node_id("region", c("n_regionkey"))),
        "customer_name": ("customer", customer, c("c_name")),
        "customer_nation": ("customer", customer, node_id("nation", c("c_nationkey"))),
        "segment": ("customer", customer, c("c_mktsegment")),
        "customer_balance": ("customer", customer, c("c_acctbal")),
        "supplier_name": ("supplier", supplier, c("s_name")),
        "supplier_nation": ("supplier", supplier, node_id("nation", c("s_nationkey"))),
        "part_name": ("part", part, c("p_name")),
        "brand": ("part", part, c("p_brand")),
        "size": ("part", part, c("p_size")),
        "ordered_by": ("orders", order, node_id("customer", c("o_custkey"))),
        "order_date": ("orders", order, c("o_orderdate")),
        "order_status": ("orders", order, c("o_orderstatus")),
        "total_price": ("orders", order, c("o_totalprice")),
        "has_part": ("lineitem", line_order, node_id("part", c("l_partkey"))),
        "supplied_by": ("lineitem", line_order, node_id("supplier", c("l_suppkey"))),
        "language": ("documents", node_id("document", c("doc_id")), c("lang")),
        "doc_source": ("documents", node_id("document", c("doc_id")), c("source")),
        "event_type": ("events", node_id("event", c("event_id")), c("event_type")),
        "event_user": ("events", node_id("event", c("event_id")), node_id("user", c("user_id"))),
        "event_time": ("events", node_id("event", c("event_id")), c("ts")),
        "event_value": ("events", node_id("event", c("event_id")), c("value")),
        "event_props": ("events", node_id("event", c("event_id")), c("props")),
        "label": ("embeddings", node_id("vector", c("vec_id")), c("label")),
        "page_url": ("pages", node_id("page", c("page_id")), c("url")),
        "page_html": ("pages", node_id("page", c("page_id")), c("html")),
    }
    return Catalog(spark, {name: Predicate(t(table), s, o, source=table) for name, (table, s, o) in p.items()})
