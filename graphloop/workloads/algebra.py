"""Patterns, paths, joins, sets, aggregates, windows and sorts."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphloop.operators import compat
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog, tables_catalog
from graphloop.plans.compiler import compile_query
from graphloop.plans.parser import parse_query
from graphloop.relation import Relation
from graphloop.sources.edges import read
from graphloop.terms import node_id, sql_id
from graphloop.workloads import sqltext as sql
from graphloop.workloads.analytics import pairs

QUERIES: dict = {}
SQL: dict[str, str] = {}

NATION, CUSTOMER, ORDER = sql_id("nation", "c_nationkey"), sql_id("customer", "c_custkey"), sql_id("order", "o_orderkey")
N, R, S = sql_id("nation", "n_nationkey"), sql_id("region", "n_regionkey"), sql_id("supplier", "s_suppkey")


def add(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return register


def sparql(name: str, query: str, text: str):
    """A query in text over the tables' graph."""
    add(name, text)(lambda spark, sf_dir: compile_query(parse_query(query), {}, tables_catalog(spark, sf_dir)).df)


sparql("bgp_single", "SELECT ?c ?n WHERE { ?c t:customer_nation ?n }", f"SELECT {CUSTOMER} AS c, {NATION} AS n FROM customer")
sparql(
    "bgp_star",
    "SELECT ?o ?d ?p WHERE { ?o t:order_date ?d ; t:total_price ?p ; t:order_status \"P\" }",
    f"SELECT {ORDER} AS o, o_orderdate AS d, o_totalprice AS p FROM orders WHERE o_orderstatus = 'P'",
)
sparql(
    "bgp_path",
    "SELECT ?o ?name WHERE { ?o t:ordered_by ?c . ?c t:customer_nation ?n . ?n t:in_region ?r . ?r t:region_name ?name }",
    f"SELECT {ORDER} AS o, r_name AS name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
)
sparql(
    "bgp_var_predicate",
    "SELECT ?p ?o WHERE { ?s ?p ?o . FILTER(?s = \"563\" || ?p = \"region_name\") }",
    "SELECT 'region_name' AS p, r_name AS o FROM region",
)


@add("bgp_self_loop", "SELECT 1::BIGINT AS x")
def bgp_self_loop(spark, sf_dir):
    catalog = Catalog(spark).add("near", spark.createDataFrame([(1, 1), (1, 2), (2, 3)], "src long, dst long"), "src", "dst")
    return compile_query(q.Pattern("?x", "near", "?x"), {}, catalog).df


# Paths

_C_R = f"SELECT {CUSTOMER} AS c, {R} AS r FROM customer JOIN nation ON c_nationkey = n_nationkey"
sparql("path_seq", "SELECT ?c ?r WHERE { ?c t:customer_nation/t:in_region ?r }", _C_R)
sparql("path_alt", "SELECT ?x ?n WHERE { ?x t:customer_nation|t:supplier_nation ?n }", f"SELECT {CUSTOMER} AS x, {NATION} AS n FROM customer UNION ALL SELECT {S}, {sql_id('nation', 's_nationkey')} FROM supplier")
sparql("path_inv", "SELECT ?n ?c WHERE { ?n ^t:customer_nation ?c }", f"SELECT {NATION} AS n, {CUSTOMER} AS c FROM customer")
sparql("path_opt", "SELECT ?a ?b WHERE { ?a t:in_region? ?b }", f"SELECT {N} AS a, {R} AS b FROM nation UNION SELECT {N}, {N} FROM nation UNION SELECT {R}, {R} FROM nation")


def chain(spark, sf_dir):
    return Catalog(spark).add("near", pairs(spark, sf_dir, "g4"), "src", "dst")


_PLUS = f"WITH RECURSIVE e AS MATERIALIZED ({sql.pairs('g4')}), r(a, b) AS (SELECT src, dst FROM e UNION SELECT r.a, e.dst FROM r JOIN e ON r.b = e.src)"
_ENDS = "SELECT src, src FROM e UNION SELECT dst, dst FROM e"


@add("path_plus", f"{_PLUS} SELECT a, b FROM r")
def path_plus(spark, sf_dir):
    return compile_query(parse_query("SELECT ?a ?b WHERE { ?a x:near+ ?b }"), {}, chain(spark, sf_dir)).df


@add("path_star", f"{_PLUS} SELECT a, b FROM r UNION {_ENDS}")
def path_star(spark, sf_dir):
    return compile_query(parse_query("SELECT ?a ?b WHERE { ?a x:near* ?b }"), {}, chain(spark, sf_dir)).df


@add("path_neg", "SELECT '2' AS a, 'y' AS b")
def path_neg(spark, sf_dir):
    catalog = Catalog(spark).add("one", spark.createDataFrame([(1, "x")], "s long, o string")).add("two", spark.createDataFrame([(2, "y")], "s long, o string"))
    return compile_query(parse_query("SELECT ?a ?b WHERE { ?a !(x:one) ?b }"), {}, catalog).df


# Joins with unbound variables

_A = [(1, None), (1, 2), (None, 2), (3, 4)]
_B = [(1, None), (None, 4), (3, 4), (5, 2)]


def unbound(spark):
    make = lambda rows, names: Relation.of(spark.createDataFrame(rows, names))
    return make([(*r, k) for k, r in enumerate(_A)], "x long, y long, i long"), make([(*r, k) for k, r in enumerate(_B)], "x long, y long, j long")


_AB = f"a AS ({sql.values([(*r, k) for k, r in enumerate(_A)], 'x, y, i')}), b AS ({sql.values([(*r, k) for k, r in enumerate(_B)], 'x, y, j')})"
_FIT = "(a.x = b.x OR a.x IS NULL OR b.x IS NULL) AND (a.y = b.y OR a.y IS NULL OR b.y IS NULL)"
_SHARE = "(a.x = b.x OR a.y = b.y)"
_BOTH = "coalesce(a.x, b.x)::BIGINT AS x, coalesce(a.y, b.y)::BIGINT AS y, i::BIGINT AS i"
add("join_unbound", f"WITH {_AB} SELECT {_BOTH}, j::BIGINT AS j FROM a JOIN b ON {_FIT}")(lambda spark, sf_dir: compat.join(*unbound(spark)).df)
add("optional_unbound", f"WITH {_AB} SELECT {_BOTH}, j::BIGINT AS j FROM a LEFT JOIN b ON {_FIT}")(lambda spark, sf_dir: compat.left_join(*unbound(spark)).df)
add("minus_unbound", f"WITH {_AB} SELECT x::BIGINT AS x, y::BIGINT AS y, i::BIGINT AS i FROM a WHERE NOT EXISTS (FROM b WHERE {_FIT} AND {_SHARE})")(lambda spark, sf_dir: compat.minus(*unbound(spark)).df)
add("exists_unbound", f"WITH {_AB} SELECT x::BIGINT AS x, y::BIGINT AS y, i::BIGINT AS i FROM a WHERE EXISTS (FROM b WHERE {_FIT})")(lambda spark, sf_dir: compat.exists(*unbound(spark), False).df)

sparql("join_natural", "SELECT ?c ?s ?n WHERE { ?c t:customer_nation ?n . ?s t:supplier_nation ?n }", f"SELECT {CUSTOMER} AS c, {S} AS s, {NATION} AS n FROM customer JOIN supplier ON c_nationkey = s_nationkey")
sparql("join_scalar", "SELECT ?r ?n WHERE { ?r t:region_name ?x . { SELECT (COUNT(?y) AS ?n) WHERE { ?y t:in_region ?z } } }", f"SELECT {sql_id('region', 'r_regionkey')} AS r, 25::BIGINT AS n FROM region")
sparql(
    "join_theta_dates",
    "SELECT ?a ?b WHERE { ?a t:ordered_by ?c ; t:order_date ?d . ?b t:ordered_by ?c ; t:order_date ?e . FILTER(?d < ?e) }",
    f"SELECT {sql_id('order', 'a.o_orderkey')} AS a, {sql_id('order', 'b.o_orderkey')} AS b FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderdate < b.o_orderdate",
)
for _hint in ("broadcast", "merge", "shuffle_hash"):
    add(f"join_hint_{_hint}", f"SELECT {CUSTOMER} AS c, {R} AS r, {NATION} AS n FROM customer JOIN nation ON c_nationkey = n_nationkey")(
        lambda spark, sf_dir, h=_hint: compile_query(q.Join(q.Pattern("?c", "customer_nation", "?n"), q.Pattern("?n", "in_region", "?r"), h), {}, tables_catalog(spark, sf_dir)).df.select("c", "r", "n")
    )


@add("asof_prev_order", "SELECT o_orderkey AS o, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before FROM orders")
def asof_prev_order(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("o"), F.lag("o_orderkey").over(w).alias("before"))


@add("interval_parent", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts > a.ts - INTERVAL 6 HOUR")
def interval_parent(spark, sf_dir):
    from graphloop.streaming.events import parents

    return parents(read(spark, sf_dir, "events"))


# Optional, minus, exists

_ORDERS_F = "orders WHERE o_orderstatus = 'F'"
sparql("optional_basic", "SELECT ?c ?o WHERE { ?c t:customer_nation <nation/3> OPTIONAL { ?o t:ordered_by ?c } }", f"SELECT {CUSTOMER} AS c, {ORDER} AS o FROM customer LEFT JOIN orders ON o_custkey = c_custkey WHERE c_nationkey = 3")
sparql(
    "optional_filter",
    "SELECT ?c ?o WHERE { ?c t:customer_nation <nation/3> ; t:customer_balance ?b OPTIONAL { ?o t:ordered_by ?c ; t:total_price ?p FILTER(?p > ?b * 40) } }",
    f"SELECT {CUSTOMER} AS c, {ORDER} AS o FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_totalprice > c_acctbal * 40 WHERE c_nationkey = 3",
)
sparql("minus_basic", "SELECT ?c WHERE { ?c t:customer_nation ?n MINUS { ?o t:ordered_by ?c } }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
sparql("minus_disjoint", "SELECT ?r WHERE { ?r t:region_name ?x MINUS { ?n t:in_region ?z } }", f"SELECT {sql_id('region', 'r_regionkey')} AS r FROM region")
sparql("exists", "SELECT ?c WHERE { ?c t:customer_nation ?n FILTER EXISTS { ?o t:ordered_by ?c ; t:order_status \"P\" } }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
sparql("not_exists", "SELECT ?c WHERE { ?c t:customer_nation ?n FILTER NOT EXISTS { ?o t:ordered_by ?c ; t:order_status \"P\" } }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
sparql("not_exists_disjoint", "SELECT ?r WHERE { ?r t:region_name ?x FILTER NOT EXISTS { ?n t:in_region ?z } }", "SELECT 1::BIGINT AS r WHERE false")

# Unions and sets

sparql("union_bag", "SELECT ?n WHERE { { ?c t:customer_nation ?n } UNION { ?s t:supplier_nation ?n } }", f"SELECT {NATION} AS n FROM customer UNION ALL SELECT {sql_id('nation', 's_nationkey')} FROM supplier")
sparql("union_ragged", "SELECT ?c ?s WHERE { { ?c t:customer_nation <nation/1> } UNION { ?s t:supplier_nation <nation/1> } }", f"SELECT {CUSTOMER} AS c, NULL::BIGINT AS s FROM customer WHERE c_nationkey = 1 UNION ALL SELECT NULL, {S} FROM supplier WHERE s_nationkey = 1")


def _sides(spark, sf_dir):
    return read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n")), read(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("n"))


for _name, _op, _call in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    add(_name, f"SELECT c_nationkey AS n FROM customer {_op} SELECT s_nationkey FROM supplier")(lambda spark, sf_dir, f=_call: f(*_sides(spark, sf_dir)))

sparql("values_block", "SELECT ?n ?tag ?name WHERE { VALUES (?n ?tag) { (<nation/1> \"a\") (<nation/2> UNDEF) } ?n t:nation_name ?name }", f"SELECT {N} AS n, CASE WHEN n_nationkey = 1 THEN 'a' END AS tag, n_name AS name FROM nation WHERE n_nationkey IN (1, 2)")
sparql("subselect", "SELECT ?n ?c WHERE { ?n t:in_region <region/2> . { SELECT ?n (COUNT(?x) AS ?c) WHERE { ?x t:customer_nation ?n } GROUP BY ?n } }", f"SELECT {N} AS n, count(*)::BIGINT AS c FROM nation JOIN customer ON c_nationkey = n_nationkey WHERE n_regionkey = 2 GROUP BY ALL")
sparql("project_rename", "SELECT (?n AS ?place) (?b * 2 AS ?twice) WHERE { ?c t:customer_nation ?n ; t:customer_balance ?b }", f"SELECT {NATION} AS place, c_acctbal * 2 AS twice FROM customer")
sparql("bind_expr", "SELECT ?c ?half WHERE { ?c t:customer_balance ?b BIND(?b / 2 AS ?half) }", f"SELECT {CUSTOMER} AS c, c_acctbal / 2 AS half FROM customer")
sparql("filter_cmp", "SELECT ?c WHERE { ?c t:customer_balance ?b FILTER(?b >= 5000 && !(?b > 9000)) }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_acctbal >= 5000 AND NOT c_acctbal > 9000")
sparql("filter_in", "SELECT ?c WHERE { ?c t:segment ?s FILTER(?s IN (\"BUILDING\", \"MACHINERY\")) }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")
sparql("filter_not_in", "SELECT ?c WHERE { ?c t:segment ?s FILTER(?s NOT IN (\"BUILDING\", \"MACHINERY\")) }", f"SELECT {CUSTOMER} AS c FROM customer WHERE c_mktsegment NOT IN ('BUILDING', 'MACHINERY')")
sparql("filter_bound", "SELECT ?c WHERE { ?c t:customer_nation ?n OPTIONAL { ?o t:ordered_by ?c } FILTER(!BOUND(?o)) }", f"SELECT {CUSTOMER} AS c FROM customer LEFT JOIN orders ON o_custkey = c_custkey WHERE o_orderkey IS NULL")
sparql("distinct", "SELECT DISTINCT ?s WHERE { ?c t:segment ?s }", "SELECT DISTINCT c_mktsegment AS s FROM customer")
sparql("ask_true", "ASK { ?n t:in_region <region/1> }", "SELECT true AS ask")
sparql("ask_false", "ASK { ?n t:in_region <region/99> }", "SELECT false AS ask")
sparql("construct", "CONSTRUCT { ?c g:lives ?n . ?n g:hosts ?c } WHERE { ?c t:customer_nation ?n . ?n t:in_region <region/1> }", f"WITH b AS (SELECT {CUSTOMER} AS c, {NATION} AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey = 1) SELECT c::VARCHAR AS s, 'lives' AS p, n::VARCHAR AS o FROM b UNION SELECT n::VARCHAR, 'hosts', c::VARCHAR FROM b")


@add("graph_clause", f"SELECT {N} AS n, {R} AS r, n_nationkey::BIGINT AS code FROM nation")
def graph_clause(spark, sf_dir):
    catalog = tables_catalog(spark, sf_dir)
    codes = read(spark, sf_dir, "nation").select(node_id("nation", F.col("n_nationkey")).alias("s"), F.col("n_nationkey").cast("long").alias("o"))
    catalog.graphs["codes"] = Catalog(spark).add("code", codes)
    return compile_query(parse_query("SELECT ?n ?r ?code WHERE { ?n t:in_region ?r . GRAPH codes { ?n x:code ?code } }"), {}, catalog).df


# Aggregates

sparql("agg_count", "SELECT ?n (COUNT(*) AS ?all) (COUNT(?o) AS ?orders) (COUNT(DISTINCT ?s) AS ?segments) WHERE { ?c t:customer_nation ?n ; t:segment ?s OPTIONAL { ?o t:ordered_by ?c } } GROUP BY ?n", f"SELECT {NATION} AS n, count(*)::BIGINT AS \"all\", count(o_orderkey)::BIGINT AS orders, count(DISTINCT c_mktsegment)::BIGINT AS segments FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_nationkey")
sparql("agg_sum_expr", "SELECT ?s (ROUND(SUM(?b * 2 + 1)) AS ?total) WHERE { ?c t:segment ?s ; t:customer_balance ?b } GROUP BY ?s", "SELECT c_mktsegment AS s, round(sum(c_acctbal * 2 + 1)) AS total FROM customer GROUP BY ALL")
sparql("agg_sum_empty", "SELECT (SUM(?b) AS ?total) (COUNT(?b) AS ?n) WHERE { ?c t:customer_balance ?b FILTER(?b > 1000000000) }", "SELECT 0.0::DOUBLE AS total, 0::BIGINT AS n")
sparql("agg_all", "SELECT ?s (MIN(?b) AS ?low) (MAX(?b) AS ?high) (COUNT(?b) AS ?n) (SAMPLE(?s) AS ?any) WHERE { ?c t:segment ?s ; t:customer_balance ?b } GROUP BY ?s", "SELECT c_mktsegment AS s, min(c_acctbal) AS low, max(c_acctbal) AS high, count(*)::BIGINT AS n, c_mktsegment AS any FROM customer GROUP BY c_mktsegment")
sparql("agg_concat", "SELECT ?r (GROUP_CONCAT(?name) AS ?names) WHERE { ?n t:in_region ?r ; t:nation_name ?name } GROUP BY ?r", f"SELECT {R} AS r, string_agg(n_name, ' ' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
sparql("agg_having", "SELECT ?n (COUNT(?c) AS ?k) WHERE { ?c t:customer_nation ?n } GROUP BY ?n HAVING(COUNT(?c) > 60)", f"SELECT {NATION} AS n, count(*)::BIGINT AS k FROM customer GROUP BY c_nationkey HAVING count(*) > 60")
sparql("agg_by_expr", "SELECT ?m (COUNT(?o) AS ?n) WHERE { ?o t:order_date ?d } GROUP BY (MONTH(?d) AS ?m)", "SELECT month(o_orderdate)::INT AS m, count(*)::BIGINT AS n FROM orders GROUP BY ALL")
sparql("agg_global", "SELECT (COUNT(*) AS ?n) WHERE { ?c t:customer_nation ?x }", "SELECT count(*)::BIGINT AS n FROM customer")


def _docs(spark, sf_dir):
    return read(spark, sf_dir, "documents")


_D = "SELECT lang, source, count(*)::BIGINT AS n FROM documents GROUP BY "
add("agg_rollup", _D + "ROLLUP (lang, source)")(lambda spark, sf_dir: _docs(spark, sf_dir).rollup("lang", "source").agg(F.count(F.lit(1)).alias("n")))
add("agg_cube", _D + "CUBE (lang, source)")(lambda spark, sf_dir: _docs(spark, sf_dir).cube("lang", "source").agg(F.count(F.lit(1)).alias("n")))
add("agg_gsets", _D + "GROUPING SETS ((lang), (source), ())")(
    lambda spark, sf_dir: _docs(spark, sf_dir).groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))
)


@add("agg_approx")
def agg_approx(spark, sf_dir):
    d = pairs(spark, sf_dir, "g7").groupBy("src").count()
    return d.agg(F.approx_count_distinct("src").alias("nodes"), F.percentile_approx("count", [0.5, 0.99], 1000).alias("degrees"))


@add("agg_argmax", "SELECT lang, source FROM (SELECT lang, source, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, source) AS k FROM documents GROUP BY lang, source) WHERE k = 1")
def agg_argmax(spark, sf_dir):
    counts = _docs(spark, sf_dir).groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    return counts.groupBy("lang").agg(F.min_by("source", F.struct((-F.col("n")).alias("n"), "source")).alias("source"))


# Windows and sorts


@add("win_topk_per_group", "SELECT c_nationkey AS n, c_custkey AS c, k::INT AS k FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) WHERE k <= 3")
def win_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy(F.col("c_acctbal").desc(), "c_custkey")
    ranked = read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n"), F.col("c_custkey").alias("c"), F.row_number().over(w).alias("k"))
    return ranked.where("k <= 3")


@add("win_ranks", "SELECT c_custkey AS c, rank() OVER w::INT AS r, dense_rank() OVER w::INT AS d FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def win_ranks(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("c"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"))


@add("win_lag_prev", "SELECT event_id AS e, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_prev(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(spark, sf_dir, "events").select(F.col("event_id").alias("e"), F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@add("win_running", "SELECT event_id AS e, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def win_running(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return read(spark, sf_dir, "events").select(F.col("event_id").alias("e"), F.count(F.lit(1)).over(w).alias("n"))


@add("win_range", "SELECT o_orderkey AS o, count(*) OVER (PARTITION BY o_custkey ORDER BY d RANGE BETWEEN 30 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM (SELECT *, date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS d FROM orders)")
def win_range(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("d").rangeBetween(-30, 0)
    days = F.datediff(F.col("o_orderdate"), F.lit("1970-01-01").cast("date"))
    return read(spark, sf_dir, "orders").withColumn("d", days).select(F.col("o_orderkey").alias("o"), F.count(F.lit(1)).over(w).alias("n"))


sparql("sort_offset", "SELECT ?c ?b WHERE { ?c t:customer_balance ?b } ORDER BY DESC(?b) ?c LIMIT 10 OFFSET 5", f"SELECT {CUSTOMER} AS c, c_acctbal AS b FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5")
sparql("sort_nulls", "SELECT ?c ?o WHERE { ?c t:customer_nation <nation/3> OPTIONAL { ?o t:ordered_by ?c } } ORDER BY ?o ?c LIMIT 7", f"SELECT {CUSTOMER} AS c, {ORDER} AS o FROM customer LEFT JOIN orders ON o_custkey = c_custkey WHERE c_nationkey = 3 ORDER BY o NULLS FIRST, c LIMIT 7")
