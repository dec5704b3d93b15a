"""Scalar functions of the expression language and of the types around it."""

from __future__ import annotations

from pyspark.sql import functions as F

from graphloop.functions.scalar import column, register
from graphloop.plans import query as q
from graphloop.plans.catalog import tables_catalog
from graphloop.plans.compiler import compile_query
from graphloop.sources.edges import read
from graphloop.workloads.analytics import pairs
from graphloop.workloads.sqltext import pairs as pairs_sql


QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, text: str | None = None):
    def inner(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return inner


def over(name: str, table: str, key: str, exprs: dict, text: str):
    """Expressions over the columns of a table, beside its key."""

    def run(spark, sf_dir):
        df = read(spark, sf_dir, table)
        return df.select(key, *(column(e, set(df.columns)).alias(n) for n, e in exprs.items()))

    add(name, text)(run)


c = q.call
over(
    "fn_math",
    "customer",
    "c_custkey",
    {
        "up": c("ceil", "?c_acctbal"),
        "down": c("floor", "?c_acctbal"),
        "size": c("abs", "?c_acctbal"),
        "root": c("round", c("sqrt", c("abs", "?c_acctbal")), 4),
        "half": c("/", "?c_acctbal", 2),
        "none": c("/", "?c_acctbal", 0),
        "rest": c("mod", "?c_custkey", 7),
        "power": c("pow", 2, c("mod", "?c_custkey", 7)),
    },
    """SELECT c_custkey, ceil(c_acctbal)::BIGINT AS up, floor(c_acctbal)::BIGINT AS down, abs(c_acctbal) AS size, round(sqrt(abs(c_acctbal)), 4) AS root,
       c_acctbal / 2 AS half, NULL::DOUBLE AS none, c_custkey % 7 AS rest, pow(2, c_custkey % 7)::DOUBLE AS power FROM customer""",
)
over(
    "fn_logic",
    "customer",
    "c_custkey",
    {"a": c("&&", c(">", "?c_acctbal", 0), c("<=", "?c_nationkey", 10)), "b": c("||", c("<", "?c_acctbal", 0), c("=", "?c_mktsegment", "BUILDING")), "same": c("sameterm", "?c_name", "?c_name"), "unbound": c("bound", "?missing")},
    "SELECT c_custkey, c_acctbal > 0 AND c_nationkey <= 10 AS a, c_acctbal < 0 OR c_mktsegment = 'BUILDING' AS b, true AS same, false AS unbound FROM customer",
)
over(
    "fn_cond",
    "customer",
    "c_custkey",
    {"kind": c("if", c(">", "?c_acctbal", 5000), "rich", "other"), "first": c("coalesce", "?missing", "?c_name")},
    "SELECT c_custkey, CASE WHEN c_acctbal > 5000 THEN 'rich' ELSE 'other' END AS kind, c_name AS first FROM customer",
)
over(
    "fn_string",
    "customer",
    "c_custkey",
    {
        "n": c("strlen", "?c_name"),
        "part": c("substr", "?c_name", 3, 4),
        "tail": c("substr", "?c_name", 5),
        "low": c("lcase", "?c_name"),
        "up": c("ucase", "?c_mktsegment"),
        "starts": c("strstarts", "?c_mktsegment", "B"),
        "ends": c("strends", "?c_mktsegment", "G"),
        "has": c("contains", "?c_mktsegment", "IL"),
        "before": c("strbefore", "?c_name", "#"),
        "after": c("strafter", "?c_name", "#"),
        "glued": c("concat", "?c_name", "-", "?c_mktsegment"),
        "encoded": c("encode_for_uri", c("concat", "?c_mktsegment", " &/")),
    },
    """SELECT c_custkey, length(c_name)::INT AS n, substr(c_name, 3, 4) AS part, substr(c_name, 5) AS tail, lower(c_name) AS low, upper(c_mktsegment) AS up,
       starts_with(c_mktsegment, 'B') AS starts, ends_with(c_mktsegment, 'G') AS ends, contains(c_mktsegment, 'IL') AS has,
       CASE WHEN contains(c_name, '#') THEN split_part(c_name, '#', 1) ELSE '' END AS before,
       CASE WHEN contains(c_name, '#') THEN substr(c_name, instr(c_name, '#') + 1) ELSE '' END AS after,
       c_name || '-' || c_mktsegment AS glued, replace(replace(replace(c_mktsegment || ' &/', ' ', '%20'), '&', '%26'), '/', '%2F') AS encoded FROM customer""",
)
over("fn_regex", "part", "p_partkey", {"hit": c("regex", "?p_brand", "#[1-3]$"), "cut": c("replace", "?p_name", "[aeiou]", "_")}, "SELECT p_partkey, regexp_matches(p_brand, '#[1-3]$') AS hit, regexp_replace(p_name, '[aeiou]', '_', 'g') AS cut FROM part")
over("fn_term", "documents", "doc_id", {"matches": c("langmatches", c("lang", "?lang"), "EN"), "numeric": c("isnumeric", "?source"), "text": c("str", "?n_chars")}, "SELECT doc_id, lower(lang) = 'en' AS matches, try_cast(source AS DOUBLE) IS NOT NULL AS \"numeric\", n_chars::VARCHAR AS text FROM documents")
over("fn_date", "orders", "o_orderkey", {"y": c("year", "?o_orderdate"), "m": c("month", "?o_orderdate"), "d": c("day", "?o_orderdate"), "h": c("hours", "?o_orderdate")}, "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS d, hour(o_orderdate)::INT AS h FROM orders")
over("fn_hash", "customer", "c_custkey", {"md5": c("md5", "?c_name"), "sha1": c("sha1", "?c_name"), "sha256": c("sha256", "?c_name")}, "SELECT c_custkey, md5(c_name) AS md5, sha1(c_name) AS sha1, sha256(c_name) AS sha256 FROM customer")
over("fn_cast", "orders", "o_orderkey", {"i": c("integer", c("str", "?o_custkey")), "bad": c("integer", "?o_orderstatus"), "x": c("double", c("str", "?o_custkey")), "b": c("boolean", "true")}, "SELECT o_orderkey, o_custkey AS i, NULL::BIGINT AS bad, o_custkey::DOUBLE AS x, true AS b FROM orders")
over("fn_json", "events", "event_id", {"k": c("json", "?props", "$.k"), "none": c("json", "?props", "$.nothing")}, "SELECT event_id, props->>'k' AS k, NULL::VARCHAR AS none FROM events")


@add("fn_array", "SELECT o_custkey AS c, len(list_distinct(list(o_orderstatus)))::INT AS kinds, array_to_string(list_sort(list(DISTINCT o_orderstatus)), ',') AS shown, max(o_orderkey) AS most FROM orders GROUP BY o_custkey")
def fn_array(spark, sf_dir):
    got = read(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c")).agg(F.collect_set("o_orderstatus").alias("s"), F.collect_list("o_orderkey").alias("k"))
    return got.select("c", F.size("s").alias("kinds"), F.array_join(F.array_sort("s"), ",").alias("shown"), F.array_max("k").alias("most"))


@add("fn_array_overlap", "SELECT a.l_orderkey AS o, count(*)::BIGINT AS shared FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) a JOIN (SELECT DISTINCT l_suppkey FROM lineitem WHERE l_orderkey < 20) b USING (l_suppkey) GROUP BY ALL")
def fn_array_overlap(spark, sf_dir):
    line = read(spark, sf_dir, "lineitem")
    few = line.where("l_orderkey < 20").agg(F.collect_set("l_suppkey").alias("few"))
    sets = line.groupBy(F.col("l_orderkey").alias("o")).agg(F.collect_set("l_suppkey").alias("s")).crossJoin(F.broadcast(few))
    return sets.where(F.arrays_overlap("s", "few")).select("o", F.size(F.array_intersect("s", "few")).cast("long").alias("shared"))


@add("fn_map", "SELECT o_custkey AS c, count(*) FILTER (o_orderstatus = 'F')::BIGINT AS f, count(DISTINCT o_orderstatus)::INT AS kinds FROM orders GROUP BY o_custkey")
def fn_map(spark, sf_dir):
    counts = read(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c"), "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("c").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))
    return maps.select("c", F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0).cast("long")).alias("f"), F.size("m").alias("kinds"))


@add("fn_html_links", """SELECT page_id, len(regexp_extract_all(html, 'href="([^"]*)"', 1))::INT AS links, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages""")
def fn_html_links(spark, sf_dir):
    pages = read(spark, sf_dir, "pages")
    return pages.select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("links"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@add("fn_vector", "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 4) AS norm2, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 4) + 0.0 AS total FROM embeddings")
def fn_vector(spark, sf_dir):
    x = F.transform("embedding", lambda v: v.cast("double"))
    total = F.aggregate(x, F.lit(0.0), lambda s, v: s + v)
    return read(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(x, F.lit(0.0), lambda s, v: s + v * v), 4).alias("norm2"), F.round(total, 4).alias("total"))


# Functions of users


@add("udf_scalar", "SELECT c_custkey, upper(substr(c_mktsegment, 1, 1)) || lower(substr(c_mktsegment, 2)) AS nice FROM customer")
def udf_scalar(spark, sf_dir):
    register("nice", F.udf(lambda s: s and s.capitalize(), "string"))
    df = read(spark, sf_dir, "customer")
    return df.select("c_custkey", column(c("nice", "?c_mktsegment"), set(df.columns)).alias("nice"))


@add("udf_pandas", "SELECT c_custkey, c_acctbal * 2 + 1 AS y FROM customer")
def udf_pandas(spark, sf_dir):
    @F.pandas_udf("double")
    def line(x):
        return x * 2 + 1

    register("line", line)
    df = read(spark, sf_dir, "customer")
    return df.select("c_custkey", column(c("line", "?c_acctbal"), set(df.columns)).alias("y"))


@add("udf_arrow", "SELECT c_custkey, c_acctbal + c_nationkey AS y FROM customer")
def udf_arrow(spark, sf_dir):
    @F.arrow_udf("double")
    def total(a, b):
        import pyarrow.compute as pc

        return pc.add(a, pc.cast(b, "double"))

    return read(spark, sf_dir, "customer").select("c_custkey", total("c_acctbal", "c_nationkey").alias("y"))


@add("udf_in_query", "SELECT 2::BIGINT << 48 AS base, count(*)::BIGINT AS n FROM nation WHERE length(n_name) > 6")
def udf_in_query(spark, sf_dir):
    register("longname", F.udf(lambda s: s is not None and len(s) > 6, "boolean"))
    found = compile_query(q.Filter(q.Pattern("?n", "nation_name", "?x"), c("longname", "?x")), {}, tables_catalog(spark, sf_dir)).df
    return found.agg(F.lit(2 << 48).cast("long").alias("base"), F.count(F.lit(1)).alias("n"))


@add("udaf_grouped", "SELECT c_nationkey::BIGINT AS n, count(*)::BIGINT AS k, round(max(c_acctbal) - min(c_acctbal), 4) AS spread FROM customer GROUP BY c_nationkey")
def udaf_grouped(spark, sf_dir):
    df = read(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("n"), "c_acctbal")

    def per_group(rows):
        import pandas as pd

        x = rows["c_acctbal"]
        return pd.DataFrame({"n": [rows["n"].iloc[0]], "k": [len(rows)], "spread": [round(float(x.max() - x.min()), 4)]})

    return df.groupBy("n").applyInPandas(per_group, "n long, k long, spread double")


@add("udtf_neighbors", f"SELECT src AS node, dst AS neighbour, row_number() OVER (PARTITION BY src ORDER BY dst)::INT AS place FROM ({pairs_sql('g3')})")
def udtf_neighbors(spark, sf_dir):
    """A table function over a graph: it takes the edges, node by node, and numbers each node's neighbours."""

    @F.udtf(returnType="node: bigint, neighbour: bigint, place: int")
    class Neighbours:
        def __init__(self):
            self.place = 0

        def eval(self, edge):
            self.place += 1
            yield edge["src"], edge["dst"], self.place

    spark.udtf.register("neighbours_of", Neighbours)
    return spark.sql("SELECT * FROM neighbours_of(TABLE(SELECT src, dst FROM {edges}) PARTITION BY src ORDER BY dst)", edges=pairs(spark, sf_dir, "g3"))
