"""Graphs, the two motivating tasks, the grid of analytics and the stress graph."""

from __future__ import annotations

from pyspark.sql import functions as F

from graphloop.algorithms import pagerank as pr
from graphloop.algorithms import structure
from graphloop.algorithms.reach import reach_avoiding
from graphloop.algorithms.vertex import bfs, both_ways, busiest_source, sssp, vertex_program
from graphloop.baselines import glue, reference
from graphloop.measure import graph_size, rank_error
from graphloop.plans.procedure import FixpointWithin, Times
from graphloop.sources import edges as views
from graphloop.sources.edges import GRAPHS, read
from graphloop.workloads import sqltext as sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
SAMPLE = [(2, 1), (3, 1), (4, 1), (4, 5), (1, 5)]
HUB_REGION, EASY_REGION = 4, 3


def add(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return register


def pairs(spark, sf_dir, graph):
    """Distinct (src, dst) of a graph."""
    return GRAPHS[graph](spark, sf_dir).select("src", "dst").distinct()


def source_of(graph, edges) -> int:
    return sql.NATION if graph == "g1" else busiest_source(edges)


def sample(spark):
    return spark.createDataFrame(SAMPLE, "src long, dst long")


SAMPLE_SQL = sql.values(SAMPLE, "src, dst")


def rounded(df, column, digits=6):
    return df.withColumn(column, F.round(column, digits))


# Graphs

for _g in ("g1", "g2", "g3", "g4", "g5", "g6", "g7", "g8"):
    add(f"edges_{_g}", f"SELECT src, dst FROM ({views.SQL[_g]})")(lambda spark, sf_dir, g=_g: GRAPHS[g](spark, sf_dir).select("src", "dst"))


@add(
    "edges_g9",
    """WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings), p AS (
      SELECT a.vec_id AS src, b.vec_id AS dst, list_dot_product(a.x, b.x) / (sqrt(list_dot_product(a.x, a.x)) * sqrt(list_dot_product(b.x, b.x))) AS w
      FROM v a JOIN v b ON a.vec_id <> b.vec_id)
      SELECT src, dst, rank::INT AS rank FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS rank FROM p) WHERE rank <= 5""",
)
def edges_g9(spark, sf_dir):
    return views.nearest_vectors(spark, sf_dir).select("src", "dst", "rank")


_SIZED = ["g1", "g2", "g3", "g4", "g5", "g6", "g7", "g8", "g10"]


_SIZES = "WITH " + ", ".join(f"{g} AS MATERIALIZED ({sql.pairs(g)})" for g in _SIZED) + " UNION ALL ".join(
    f" SELECT '{g}' AS graph, (SELECT count(*) FROM (SELECT src::VARCHAR FROM {g} UNION SELECT dst::VARCHAR FROM {g}))::BIGINT AS nodes, (SELECT count(*) FROM {g})::BIGINT AS edges"
    for g in _SIZED
)


@add("graph_sizes", _SIZES)
def graph_sizes(spark, sf_dir):
    parts = [graph_size(GRAPHS[g](spark, sf_dir)).select(F.lit(g).alias("graph"), "nodes", "edges") for g in _SIZED]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


# Constrained reachability


def lanes(spark, sf_dir):
    return both_ways(pairs(spark, sf_dir, "g1"))


def region(spark, sf_dir, key):
    return read(spark, sf_dir, "nation").where(F.col("n_regionkey") == key).select(F.col("n_nationkey").cast("long").alias("node"))


def reach_sql(closed: int, start: int, edges: str | None = None, direction: str = "out") -> str:
    e = edges or "SELECT src, dst FROM g UNION SELECT dst, src FROM g"
    a, b = ("src", "dst") if direction == "out" else ("dst", "src")
    return f"""WITH RECURSIVE g AS MATERIALIZED ({sql.pairs('g1')}), e AS MATERIALIZED ({e}), ok AS (SELECT n_nationkey::BIGINT AS node FROM nation WHERE n_regionkey <> {closed}),
      r(node) AS (SELECT {b} FROM e JOIN ok ON {b} = node WHERE {a} = {start} UNION SELECT e.{b} FROM r JOIN e ON r.node = e.{a} JOIN ok ON e.{b} = ok.node)
      SELECT node FROM r"""


for _name, _closed, _start in (("reach_closed_hub", HUB_REGION, 5), ("reach_avoid", EASY_REGION, 5), ("reach_nothing", HUB_REGION, 0)):
    add(_name, reach_sql(_closed, _start))(
        lambda spark, sf_dir, c=_closed, s=_start: reach_avoiding(lanes(spark, sf_dir), s, region(spark, sf_dir, c)).df
    )


@add("reach_avoid_in", reach_sql(EASY_REGION, 5, "SELECT src, dst FROM g", "in"))
def reach_avoid_in(spark, sf_dir):
    return reach_avoiding(pairs(spark, sf_dir, "g1"), 5, region(spark, sf_dir, EASY_REGION), direction="in").df


def check(name: str, differences: int, spark):
    return spark.createDataFrame([(name, differences)], "check string, differences long")


def zero(name: str) -> str:
    return f"SELECT '{name}' AS \"check\", 0::BIGINT AS differences"


def differ(a, b) -> int:
    """Rows of one bag that the other lacks, both ways."""
    b = b.select(a.columns)
    return a.exceptAll(b).count() + b.exceptAll(a).count()


@add("reach_delta_equals_naive", zero("reach_delta_equals_naive"))
def reach_delta_equals_naive(spark, sf_dir):
    e, blocked = lanes(spark, sf_dir), region(spark, sf_dir, HUB_REGION)
    return check("reach_delta_equals_naive", differ(reach_avoiding(e, 5, blocked).df, reach_avoiding(e, 5, blocked, rewrite=False).df), spark)


# PageRank and p-index


def author(spark, sf_dir):
    return read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("node"), F.col("o_custkey").alias("author"))


def names(spark, sf_dir):
    return read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("author"), F.col("c_name").alias("name"))


_TOP = sql.pagerank(sql.pairs("g2")) + ", a AS (SELECT o_custkey AS author, sum(rank) AS p_index FROM r10 JOIN orders ON node = o_orderkey GROUP BY o_custkey)"


@add("pindex_all", _TOP + " SELECT author, round(p_index, 6) AS p_index FROM a")
def pindex_all(spark, sf_dir):
    rank = pr.pagerank(pairs(spark, sf_dir, "g2")).df
    return rounded(pr.p_index(rank, author(spark, sf_dir), None), "p_index")


@add("pindex_top", _TOP + " SELECT author, round(p_index, 6) AS p_index FROM a ORDER BY a.p_index DESC, author LIMIT 1")
def pindex_top(spark, sf_dir):
    return rounded(pr.p_index(pr.pagerank(pairs(spark, sf_dir, "g2")).df, author(spark, sf_dir), 1), "p_index")


@add("pindex_top5_named", _TOP + " SELECT author, c_name AS name, round(p_index, 6) AS p_index FROM (SELECT * FROM a ORDER BY p_index DESC, author LIMIT 5) JOIN customer ON author = c_custkey")
def pindex_top5_named(spark, sf_dir):
    return rounded(pr.p_index(pr.pagerank(pairs(spark, sf_dir, "g2")).df, author(spark, sf_dir), 5, names(spark, sf_dir)), "p_index")


@add("glue_pindex", _TOP + " SELECT author, round(p_index, 6) AS p_index FROM a ORDER BY a.p_index DESC, author LIMIT 5")
def glue_pindex(spark, sf_dir):
    return rounded(glue.glue_pindex(pairs(spark, sf_dir, "g2"), author(spark, sf_dir))[0], "p_index")


@add("pr_10", sql.pagerank(sql.pairs("g2")) + " SELECT node, round(rank, 6) AS rank FROM r10")
def pr_10(spark, sf_dir):
    return rounded(pr.pagerank(pairs(spark, sf_dir, "g2")).df, "rank")


@add("pr_damping_05", sql.pagerank(sql.pairs("g2"), damping=0.5) + " SELECT node, round(rank, 6) AS rank FROM r10")
def pr_damping_05(spark, sf_dir):
    return rounded(pr.pagerank(pairs(spark, sf_dir, "g2"), damping=0.5).df, "rank")


@add("pr_paper_sample", sql.pagerank(SAMPLE_SQL) + " SELECT node::BIGINT AS node, round(rank, 9) AS rank FROM r10")
def pr_paper_sample(spark, sf_dir):
    return rounded(pr.pagerank(sample(spark)).df, "rank", 9)


def _first_round(spark, sf_dir):
    return pr.run(pr.pagerank_procedure(until=Times(1)), pr.graph_catalog(pairs(spark, sf_dir, "g2"))).env


_ONE = sql.pagerank(sql.pairs("g2"), 1)
add("pr_nodes", f"{_ONE} SELECT node FROM nodes")(lambda spark, sf_dir: _first_round(spark, sf_dir)["place"].df)
add("pr_n", f"{_ONE} SELECT n::BIGINT AS n FROM n")(lambda spark, sf_dir: _first_round(spark, sf_dir)["size"].df.select(F.col("many").alias("n")))


@add("pr_share_1", f"{_ONE} SELECT node, round(share, 6) AS share FROM s1")
def pr_share_1(spark, sf_dir):
    return _first_round(spark, sf_dir)["sent"].df.select(F.col("to").alias("node"), F.round(F.col("gain").cast("double"), 6).alias("share"))


@add("pr_leftover_1", f"{_ONE} SELECT round(1 - sum(share), 6) AS leftover FROM s1")
def pr_leftover_1(spark, sf_dir):
    env = _first_round(spark, sf_dir)
    return env["dealt"].df.crossJoin(env["size"].df).select(F.round((F.col("base") * F.col("many")).cast("double"), 6).alias("leftover"))


@add("pr_degree", f"SELECT src AS node, count(*)::BIGINT AS degree FROM ({sql.pairs('g2')}) GROUP BY src")
def pr_degree(spark, sf_dir):
    return pr.out_degree(pairs(spark, sf_dir, "g2"))


@add("pr_rank0", _ONE + " SELECT node, round(rank, 9) AS rank FROM r0")
def pr_rank0(spark, sf_dir):
    nodes = pr.node_set(pairs(spark, sf_dir, "g2"))
    return nodes.crossJoin(F.broadcast(nodes.agg(F.count(F.lit(1)).alias("n")))).select("node", F.round(F.lit(1.0) / F.col("n"), 9).alias("rank"))


@add("pr_mass_is_one", "SELECT range::BIGINT AS round, 1.0::DOUBLE AS mass FROM range(1, 6)")
def pr_mass_is_one(spark, sf_dir):
    e, rows = pairs(spark, sf_dir, "g4"), []
    for k in range(1, 6):
        rows.append((k, round(pr.pagerank(e, until=Times(k)).df.agg(F.sum("rank")).first()[0], 6)))
    return spark.createDataFrame(rows, "round long, mass double")


@add("pr_hoisted_equals_plain", zero("pr_hoisted_equals_plain"))
def pr_hoisted_equals_plain(spark, sf_dir):
    e = pairs(spark, sf_dir, "g3")
    a, b = (rounded(pr.pagerank(e, until=Times(3), hoist=h).df, "rank", 9) for h in (True, False))
    return check("pr_hoisted_equals_plain", differ(a, b), spark)


_ROUNDS = 15


def _stops(measure: str, test: str) -> str:
    """Rounds and the measure at the first round that passes the test, over unrolled rounds."""
    parts = " UNION ALL ".join(f"SELECT {k} AS k, {measure} AS m FROM r{k} a JOIN r{k - 1} b USING (node)" for k in range(1, _ROUNDS + 1))
    return f"{sql.pagerank(sql.pairs('g2'), _ROUNDS)}, moves AS ({parts}) SELECT k::BIGINT AS rounds, round(m, 6)::DOUBLE AS measured FROM moves WHERE {test} ORDER BY k LIMIT 1"


def _stopped(spark, sf_dir, until, seen):
    found = pr.pagerank(pairs(spark, sf_dir, "g2"), until=until)
    return spark.createDataFrame([(found.rounds[0], round(seen[-1], 6))], "rounds long, measured double")


@add("pr_residual_stop", _stops("sum(abs(a.rank - b.rank))", "m < 1e-3"))
def pr_residual_stop(spark, sf_dir):
    seen = []
    return _stopped(spark, sf_dir, pr.residual_below(1e-3, seen=seen), seen)


@add("pr_corr_stop", _stops("CASE WHEN stddev_pop(b.rank) > 1e-12 THEN corr(a.rank, b.rank) END", "m > 0.9999"))
def pr_corr_stop(spark, sf_dir):
    seen = []
    return _stopped(spark, sf_dir, pr.correlation_above(0.9999, seen), seen)


@add("pr_tol", _stops("max(abs(a.rank - b.rank))", "m <= 1e-4"))
def pr_tol(spark, sf_dir):
    """A fixpoint within a tolerance, and how far the last round moved any rank: one round more tells."""
    e = pairs(spark, sf_dir, "g2")
    rounds = pr.pagerank(e, until=FixpointWithin("held", "node", "rank", 1e-4)).rounds[0]
    last = pr.pagerank(e, until=Times(rounds)).df
    before = pr.pagerank(e, until=Times(rounds - 1)).df if rounds > 1 else pr_rank0(spark, sf_dir)
    moved = last.join(before.withColumnRenamed("rank", "old"), "node").agg(F.max(F.abs(F.col("rank") - F.col("old")))).first()[0]
    return spark.createDataFrame([(rounds, round(moved, 6))], "rounds long, measured double")


@add("rank_error", zero("rank_error"))
def rank_error_query(spark, sf_dir):
    e = pairs(spark, sf_dir, "g4")
    expected = reference.pagerank([tuple(r) for r in e.collect()])
    return check("rank_error", int(rank_error(pr.pagerank(e).df, expected) > 1e-9), spark)


# The grid and the stress graph


def _bfs(spark, sf_dir, g):
    e = pairs(spark, sf_dir, g)
    return bfs(e, source_of(g, e))


def _sssp(spark, sf_dir, g):
    e = pairs(spark, sf_dir, g)
    return rounded(sssp(e, source_of(g, e)), "dist")


_TASKS = {
    "bfs": (_bfs, sql.bfs),
    "sssp": (_sssp, lambda g: sql.sssp(g, False)),
    "wcc": (lambda spark, sf_dir, g: structure.wcc(pairs(spark, sf_dir, g)), sql.wcc),
    "lcc": (lambda spark, sf_dir, g: rounded(structure.lcc(pairs(spark, sf_dir, g)), "lcc"), sql.lcc),
    "pr": (lambda spark, sf_dir, g: rounded(pr.pagerank(pairs(spark, sf_dir, g)).df, "rank"), lambda g: sql.pagerank(sql.pairs(g)) + " SELECT node, round(rank, 6) AS rank FROM r10"),
}
for _task, (_run, _text) in _TASKS.items():
    for _g in ("g1", "g2", "g3", "g4", "g5", "g6", "g7"):
        add(f"{_task}_{_g}", _text(_g))(lambda spark, sf_dir, g=_g, f=_run: f(spark, sf_dir, g))


@add("cdlp_g7", sql.cdlp(sql.pairs("g7"), 10))
def cdlp_g7(spark, sf_dir):
    return structure.cdlp(pairs(spark, sf_dir, "g7"))


@add("cdlp_labeled", sql.cdlp(sql.pairs("g6"), 3, f"SELECT node, coalesce(s_nationkey, -1)::BIGINT AS label FROM nodes LEFT JOIN supplier ON node = {views.sql_id('supplier', 's_suppkey')}"))
def cdlp_labeled(spark, sf_dir):
    e = pairs(spark, sf_dir, "g6")
    known = read(spark, sf_dir, "supplier").select(views.node_id("supplier", F.col("s_suppkey")).alias("node"), F.col("s_nationkey").cast("long").alias("label"))
    labels = pr.node_set(e).join(known, "node", "left").na.fill(-1, ["label"])
    return structure.cdlp(e, 3, labels)


@add("sssp_weighted", sql.sssp("g7", True))
def sssp_weighted(spark, sf_dir):
    e = GRAPHS["g7"](spark, sf_dir)
    return rounded(sssp(e, busiest_source(e), "weight"), "dist")


@add("bfs_undirected", sql.bfs("g3").replace(f"e AS MATERIALIZED ({sql.pairs('g3')})", f"d AS MATERIALIZED ({sql.pairs('g3')}), e AS MATERIALIZED (SELECT src, dst FROM d UNION SELECT dst, src FROM d)").replace(sql.source("g3"), "(SELECT src FROM d GROUP BY src ORDER BY count(*) DESC, src LIMIT 1)"))
def bfs_undirected(spark, sf_dir):
    e = pairs(spark, sf_dir, "g3")
    return bfs(e, busiest_source(e), directed=False)


@add("wcc_star_equals_minlabel", zero("wcc_star_equals_minlabel"))
def wcc_star_equals_minlabel(spark, sf_dir):
    e = pairs(spark, sf_dir, "g4")
    star = structure.wcc(e, local=False)
    return check("wcc_star_equals_minlabel", differ(star, structure.wcc(e, "minlabel")) + differ(star, structure.wcc(e)), spark)


@add("vp_equals_bfs", zero("vp_equals_bfs"))
def vp_equals_bfs(spark, sf_dir):
    e = pairs(spark, sf_dir, "g2")
    start = busiest_source(e)
    state = spark.createDataFrame([(start, 0)], "node long, value long")
    found = vertex_program(e, state, F.col("value") + 1).df.select("node", F.col("value").alias("level"))
    return check("vp_equals_bfs", differ(found, bfs(e, start)), spark)


@add("triangles", f"WITH p AS MATERIALIZED (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ({sql.pairs('g7')}) WHERE src <> dst) SELECT count(*)::BIGINT AS n FROM p x JOIN p y ON x.b = y.a JOIN p z ON z.a = x.a AND z.b = y.b")
def triangles(spark, sf_dir):
    return structure.triangles(pairs(spark, sf_dir, "g7")).agg(F.count(F.lit(1)).alias("n"))
