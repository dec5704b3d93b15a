"""Recursion, machines, colour refinement, local procedures and message passing."""

from __future__ import annotations

from pyspark.sql import functions as F

from graphloop.algorithms import neural, procedures, structure, turing
from graphloop.algorithms.pagerank import node_set
from graphloop.algorithms.reach import graph_catalog, reach_avoiding
from graphloop.baselines.glue import sql_ancestors
from graphloop.materialize import durable
from graphloop.plans import locality, recursion
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.parser import parse_procedure
from graphloop.plans.procedure import Procedure, Times
from graphloop.plans.runtime import empty_relation, run
from graphloop.sources.edges import read
from graphloop.workloads import sqltext as sql
from graphloop.workloads.analytics import HUB_REGION
from graphloop.workloads.analytics import SQL as GRAPH_SQL
from graphloop.workloads.analytics import lanes, pairs, region, rounded
from graphloop.workloads.language import REACH

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return register


# Recursive queries

_EDGE = q.Project(q.Extend(q.Pattern("?s", "step", "?o"), "p", q.Const("up")), ("s", "p", "o"))
_EDGE_P = q.Project(q.Pattern("?s", "step", "?o"), ("s", (q.Const("up"), "p"), "o"))
_LONGER = q.Project(
    q.Join(q.Project(q.VarRef("graph"), ("s", "p", (q.Var("o"), "m"))), q.Project(q.Pattern("?m", "step", "?o"), ("m", "o"))), ("s", "p", "o")
)
ANCESTORS = recursion.RecursiveQuery(q.Union(_EDGE_P, _LONGER), q.Project(q.VarRef("graph"), ("s", "o")))


def closure_sql(edges: str) -> str:
    return f"WITH RECURSIVE e AS MATERIALIZED ({edges}), r(s, o) AS (SELECT src, dst FROM e UNION SELECT r.s, e.dst FROM r JOIN e ON r.o = e.src) SELECT s, o FROM r"


@add("rec_ancestors", closure_sql(sql.pairs("g5")))
def rec_ancestors(spark, sf_dir):
    from graphloop.plans.compiler import closure

    return closure(pairs(spark, sf_dir, "g5").select(F.col("src").alias("s"), F.col("dst").alias("o")))


@add("rec_least_fixpoint", closure_sql(sql.pairs("g4")))
def rec_least_fixpoint(spark, sf_dir):
    return recursion.recursive_graph(ANCESTORS, graph_catalog(pairs(spark, sf_dir, "g4"))).df


@add("rec_translated", closure_sql(sql.pairs("g4")))
def rec_translated(spark, sf_dir):
    catalog = graph_catalog(pairs(spark, sf_dir, "g4"))
    start = {"graph": empty_relation(catalog, "s long, p string, o long")}
    return run(recursion.to_procedure(ANCESTORS), catalog, strict=False, env=start).df


@add("rec_cycle", closure_sql(sql.values([(1, 2), (2, 3), (3, 4), (4, 1)], "src, dst")).replace("SELECT s, o FROM r", "SELECT s::BIGINT AS s, o::BIGINT AS o FROM r"))
def rec_cycle(spark, sf_dir):
    edges = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 1)], "src long, dst long")
    return recursion.recursive_graph(ANCESTORS, graph_catalog(edges)).df


def _flip():
    """A step that takes back what it made: it has no fixpoint."""
    made = q.Values(("s", "p", "o"), ((1, "on", 1),))
    return recursion.RecursiveQuery(q.Exists(made, q.VarRef("graph"), negated=True), q.VarRef("graph"))


@add("rec_partial_cycle", "SELECT 1::BIGINT AS s, 'on' AS p, 1::BIGINT AS o WHERE false")
def rec_partial_cycle(spark, sf_dir):
    return recursion.recursive_graph(_flip(), Catalog(spark), "partial").df


@add("rec_partial_reached", closure_sql(sql.pairs("g4")))
def rec_partial_reached(spark, sf_dir):
    return recursion.recursive_graph(recursion.RecursiveQuery(q.Union(_EDGE, _LONGER), ANCESTORS.select), graph_catalog(pairs(spark, sf_dir, "g4")), "partial").df


@add("rec_monotone_report", sql.values([("bind", 1), ("minus", 1), ("negation", 1), ("optional", 1), ("union", 0)], "name, issues"))
def rec_monotone_report(spark, sf_dir):
    p = q.Pattern("?s", "step", "?o")
    cases = {
        "union": ANCESTORS.step,
        "bind": _EDGE,
        "minus": q.Minus(p, q.VarRef("graph")),
        "negation": q.Exists(p, q.VarRef("graph"), negated=True),
        "optional": q.Join(q.LeftJoin(p, q.Pattern("?x", "step", "?y")), q.Pattern("?y", "step", "?z")),
    }
    return spark.createDataFrame([(n, len(recursion.check_monotone(x))) for n, x in cases.items()], "name string, issues int")


@add("sqlrec_ancestors", closure_sql(sql.pairs("g4")))
def sqlrec_ancestors(spark, sf_dir):
    return sql_ancestors(pairs(spark, sf_dir, "g4"))


@add("adom_outside_reach", "SELECT 's' AS var, 'x' AS value WHERE false")
def adom_outside_reach(spark, sf_dir):
    catalog = graph_catalog(lanes(spark, sf_dir), region(spark, sf_dir, HUB_REGION))
    return locality.outside_domain(reach_avoiding(lanes(spark, sf_dir), 5, region(spark, sf_dir, HUB_REGION)).df, catalog)


@add("adom_report", "SELECT 'pagerank' AS name, true AS invents UNION ALL SELECT 'reach', false")
def adom_report(spark, sf_dir):
    texts = {"reach": REACH, "pagerank": procedures.text_of("pr")}
    rows = [(name, bool(locality.invents_values(parse_procedure(text)))) for name, text in texts.items()]
    return spark.createDataFrame(rows, "name string, invents boolean")


@add("adom_bound", f"WITH e AS MATERIALIZED ({sql.pairs('g7')}) SELECT count(*)::BIGINT + 1 AS bound FROM (SELECT src FROM e UNION SELECT dst FROM e)")
def adom_bound(spark, sf_dir):
    bound = locality.domain_bound(spark.createDataFrame([(1,)], "s long"), graph_catalog(durable(pairs(spark, sf_dir, "g7"))))
    return spark.createDataFrame([(bound,)], "bound long")


# Machines


@add("tm_accepts_parity", "SELECT * FROM (VALUES ('', true), ('1', false), ('11', true), ('111', false), ('1111', true)) t(word, accepted)")
def tm_accepts_parity(spark, sf_dir):
    rows = [(w, not turing.run_machine(turing.PARITY, w, spark).df.isEmpty()) for w in ("", "1", "11", "111", "1111")]
    return spark.createDataFrame(rows, "word string, accepted boolean")


@add("tm_unary_increment", "SELECT range::BIGINT AS pos, '1' AS symbol FROM range(0, 4)")
def tm_unary_increment(spark, sf_dir):
    return turing.run_machine(turing.INCREMENT, "111", spark).df.where("symbol <> '_'")


@add("tm_binary_increment", "SELECT * FROM (VALUES (0::BIGINT, '0'), (1, '0'), (2, '1')) t(pos, symbol)")
def tm_binary_increment(spark, sf_dir):
    return turing.run_machine(turing.BINARY_INCREMENT, "110", spark).df


@add("tm_memory_ratio", "SELECT true AS linear")
def tm_memory_ratio(spark, sf_dir):
    found = turing.run_machine(turing.INCREMENT, "11111", spark)
    most = max(t["rows"] or 0 for t in found.trace if t["var"] == "tape")
    return spark.createDataFrame([(most <= 5 + 1,)], "linear boolean")


# Colour refinement and local procedures


def regions(spark, sf_dir):
    return read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("node"), F.col("n_regionkey").cast("long").alias("label"))


def one_label(edges):
    return node_set(edges).withColumn("label", F.lit(0).cast("long"))


_VECTOR_LABELS = "SELECT vec_id AS node, label FROM embeddings"
_G9 = f"SELECT src, dst FROM ({GRAPH_SQL['edges_g9']})"
_PLAIN = "SELECT src AS node, 0 AS label FROM e UNION SELECT dst, 0 FROM e"


@add("wl_rounds_k", sql.colours(_G9, _VECTOR_LABELS, 2) + " SELECT node, class FROM w2")
def wl_rounds_k(spark, sf_dir):
    labels = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), "label")
    return structure.weisfeiler_lehman(pairs(spark, sf_dir, "g9"), labels, 2)[0]


@add("wl_stable", sql.colours(sql.pairs("g3"), _PLAIN, 12) + " SELECT node, class FROM w12")
def wl_stable(spark, sf_dir):
    e = pairs(spark, sf_dir, "g3")
    return structure.weisfeiler_lehman(e, one_label(e))[0]


@add("wl_classes", sql.colours(sql.pairs("g3"), _PLAIN, 2) + " SELECT * FROM (SELECT 0::BIGINT AS round, count(DISTINCT class)::BIGINT AS classes FROM w0 UNION ALL SELECT 1, count(DISTINCT class) FROM w1 UNION ALL SELECT 2, count(DISTINCT class) FROM w2)")
def wl_classes(spark, sf_dir):
    e = pairs(spark, sf_dir, "g3")
    sizes = structure.weisfeiler_lehman(e, one_label(e), 2)[1]
    return spark.createDataFrame(list(enumerate(sizes[:3])), "round long, classes long")


@add("wl_regular_pair", "SELECT 1::BIGINT AS classes")
def wl_regular_pair(spark, sf_dir):
    """A hexagon and two triangles are not told apart."""
    ring = [(k, (k + 1) % 6) for k in range(6)] + [(10, 11), (11, 12), (12, 10), (13, 14), (14, 15), (15, 13)]
    e = spark.createDataFrame(ring, "src long, dst long")
    return structure.weisfeiler_lehman(e, one_label(e))[0].agg(F.count_distinct("class").alias("classes"))


def _local(spark, sf_dir, rounds=2):
    edges, labels = lanes(spark, sf_dir), regions(spark, sf_dir)
    proc = neural.local_wl_procedure(["near"], rounds)
    return proc, run(proc, neural.label_catalog(spark, edges, labels), mode="batched").df


@add("local_wl", sql.colours(sql.pairs("g1"), "SELECT n_nationkey::BIGINT AS node, n_regionkey AS label FROM nation", 2) + " SELECT node, class FROM w2")
def local_wl(spark, sf_dir):
    found = _local(spark, sf_dir)[1]
    least = found.groupBy("lab").agg(F.min("v").alias("class"))
    return found.join(least, "lab").select(F.col("v").alias("node"), "class")


@add("local_bound_violations", "SELECT 0::BIGINT AS violations")
def local_bound_violations(spark, sf_dir):
    classes = structure.weisfeiler_lehman(lanes(spark, sf_dir), regions(spark, sf_dir), 2)[0]
    return neural.bound_violations(_local(spark, sf_dir)[1], classes).agg(F.count(F.lit(1)).alias("violations"))


@add("local_report", sql.values([("constant", 1), ("graph in loop", 2), ("local", 0)], "name, issues"))
def local_report(spark, sf_dir):
    good = neural.local_wl_procedure(["near"], 1)
    *lets, loop, ret = good.statements
    graph = Procedure().let("vector", q.Pattern("?v", "near", "?lab")).statements[0]
    constant = Procedure().let("vector", q.Filter(q.VarRef("vector"), q.call("=", "?lab", 1)), split=loop.body[0].split).statements[0]
    loops = {"local": good, "graph in loop": Procedure([*lets, *Procedure().loop([graph], Times(1)).statements, ret]), "constant": Procedure([*lets, *Procedure().loop([constant], Times(1)).statements, ret])}
    return spark.createDataFrame([(n, len(locality.check_local(p))) for n, p in loops.items()], "name string, issues int")


# Message passing

_X = "SELECT vec_id AS node, unnest(embedding)::DOUBLE AS value, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings"


def no_minus_zero(value: str) -> str:
    return f"CASE WHEN round({value}, 4) = 0 THEN 0.0 ELSE round({value}, 4) END::DOUBLE"


def gnn_sql(layers: list[tuple[str, float, float, str]], end: str = f"SELECT node, pos::INT AS pos, {no_minus_zero('value')} AS value FROM x{{n}}") -> str:
    steps = [f"WITH e AS MATERIALIZED ({_G9})", f"x0 AS MATERIALIZED ({_X})"]
    for k, (agg, own, near, act) in enumerate(layers, 1):
        heard = f"SELECT e.src AS node, pos, {agg}(value) AS h FROM e JOIN x{k - 1} ON e.dst = node GROUP BY e.src, pos"
        value = f"value * {own} + coalesce(h, 0) * {near}"
        steps.append(f"x{k} AS MATERIALIZED (SELECT node, pos, {act.format(value)} AS value FROM x{k - 1} LEFT JOIN ({heard}) USING (node, pos))")
    return ", ".join(steps) + " " + end.format(n=len(layers))


def vectors(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), F.col("embedding").alias("x"))


def _gnn(name, layers, text, **options):
    add(name, text)(lambda spark, sf_dir: rounded(neural.gnn(pairs(spark, sf_dir, "g9"), vectors(spark, sf_dir), layers, **options), "value", 4))


_gnn("gnn_sum_1", [neural.Layer("sum", 1.0, 0.5)], gnn_sql([("sum", 1.0, 0.5, "{}")]))
_gnn("gnn_mean_2", [neural.Layer("mean", 0.5, 0.5, act="relu")] * 2, gnn_sql([("avg", 0.5, 0.5, "greatest({}, 0)")] * 2))
_gnn("gnn_max_1", [neural.Layer("max", 0.0, 1.0)], gnn_sql([("max", 0.0, 1.0, "{}")]))
_gnn("gnn_readout", [neural.Layer("mean", 1.0, 1.0)], gnn_sql([("avg", 1.0, 1.0, "{}")], "SELECT pos::INT AS pos, round(sum(value), 4) AS value FROM x{n} GROUP BY pos"), readout="sum")

_TURN = [[0.0] * 64 for _ in range(64)]
for _i in range(64):
    _TURN[_i][(_i + 1) % 64] = 2.0
_gnn(
    "gnn_matrix",
    [neural.Layer("sum", 1.0, _TURN)],
    f"WITH e AS MATERIALIZED ({_G9}), x AS MATERIALIZED ({_X}), h AS (SELECT e.src AS node, pos, sum(value) AS h FROM e JOIN x ON e.dst = node GROUP BY e.src, pos) SELECT x.node, x.pos::INT AS pos, {no_minus_zero('value + 2 * coalesce(h, 0)')} AS value FROM x LEFT JOIN h ON h.node = x.node AND h.pos = (x.pos + 1) % 64",
)


@add(
    "gnn_edge_update",
    f"WITH e AS MATERIALIZED ({_G9}), x AS MATERIALIZED ({_X}) SELECT e.src, e.dst, a.pos::INT AS pos, {no_minus_zero('a.value - b.value')} AS value FROM e JOIN x a ON e.src = a.node JOIN x b ON e.dst = b.node AND a.pos = b.pos",
)
def gnn_edge_update(spark, sf_dir):
    states = neural.edge_states(pairs(spark, sf_dir, "g9"), vectors(spark, sf_dir), [neural.Layer()], lambda kept, own, other: kept + own - other)
    return rounded(states, "value", 4)
