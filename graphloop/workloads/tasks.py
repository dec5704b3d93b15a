"""The grid and the stress graph by procedures of the language, in all modes; and the p-index task as one procedure."""

from __future__ import annotations

from pyspark.sql import functions as F

from graphloop.algorithms import pagerank as pr
from graphloop.algorithms import procedures
from graphloop.plans.catalog import tables_catalog
from graphloop.plans.parser import parse_procedure
from graphloop.plans.rewrite import optimise
from graphloop.plans.runtime import INLINE_ROWS, InlineLimit, TimeLimit, run
from graphloop.terms import sql_id
from graphloop.workloads import sqltext as sql
from graphloop.workloads.analytics import SAMPLE_SQL, _TASKS, _TOP, pairs, rounded, sample

QUERIES: dict = {}
SQL: dict[str, str] = {}
LIMIT_S = 600

TEXT = {name: made for name, (_, made) in _TASKS.items()}
TEXT["cdlp"] = lambda g: sql.cdlp(sql.pairs(g), 10)


def add(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return register


def solved(spark, sf_dir, name, graph, mode="plan", **more):
    """The answer of a task, rounded as its SQL is; it takes the time it needs."""
    found = procedures.solve(name, pairs(spark, sf_dir, graph), sql.NATION if graph == "g1" else None, mode, **more)
    df = procedures.result(name, found)
    return rounded(df, df.columns[1]) if dict(df.dtypes)[df.columns[1]] == "double" else df


for _name in ("bfs", "lcc", "pr", "sssp", "wcc"):
    for _g in ("g1", "g2", "g3", "g4", "g5", "g6"):
        add(f"proc_{_name}_{_g}", TEXT[_name](_g))(lambda spark, sf_dir, n=_name, g=_g: solved(spark, sf_dir, n, g))
    add(f"inline_{_name}_g1", TEXT[_name]("g1"))(lambda spark, sf_dir, n=_name: solved(spark, sf_dir, n, "g1", "inline"))
for _name in TEXT:
    add(f"proc_{_name}_g7", TEXT[_name]("g7"))(lambda spark, sf_dir, n=_name: solved(spark, sf_dir, n, "g7"))
    add(f"stress_batched_{_name}", TEXT[_name]("g7"))(lambda spark, sf_dir, n=_name: solved(spark, sf_dir, n, "g7", "batched", buckets=2))
    add(f"stress_lifted_{_name}", TEXT[_name]("g7"))(lambda spark, sf_dir, n=_name: solved(spark, sf_dir, n, "g7", "batched", how="lifted"))


@add("stress_inline", f"SELECT unnest(['bfs', 'cdlp', 'lcc', 'pr', 'sssp', 'wcc']) AS algorithm, CASE WHEN n > {INLINE_ROWS} THEN 'too long' ELSE 'ok' END AS status FROM (SELECT count(*) AS n FROM ({sql.pairs('g7')}))")
def stress_inline(spark, sf_dir):
    """What becomes of the algorithms on the stress graph if values are written into the queries."""
    rows = []
    for name in sorted(TEXT):
        try:
            solved(spark, sf_dir, name, "g7", "inline", timeout_s=LIMIT_S).count()
            rows.append((name, "ok"))
        except InlineLimit:
            rows.append((name, "too long"))
        except TimeLimit:
            rows.append((name, "timeout"))
    return spark.createDataFrame(rows, "algorithm string, status string")


@add("batch_queries", f"""WITH b AS ({sql.bfs('g4')}) SELECT 'bfs' AS algorithm, 4 * (max(level) + 1)::BIGINT AS queries FROM b UNION ALL SELECT 'sssp', 4 * (max(level) + 1)::BIGINT FROM b
  UNION ALL SELECT unnest(['cdlp', 'pr', 'lcc']), unnest([40, 40, 4])::BIGINT""".replace("WITH b AS (WITH RECURSIVE", "WITH b AS (WITH RECURSIVE"))
def batch_queries(spark, sf_dir):
    """How many queries bucketed evaluation needs: buckets times the rounds of the sending statement."""
    rows = []
    for name in ("bfs", "sssp", "cdlp", "pr", "lcc"):
        found = procedures.solve(name, pairs(spark, sf_dir, "g4"), mode="batched")
        rows.append((name, sum(t["batches"] for t in found.trace)))
    return spark.createDataFrame(rows, "algorithm string, queries long")


for _how in ("bucketed", "lifted", "per_value"):
    _edges = SAMPLE_SQL if _how == "per_value" else sql.pairs("g4")
    add(f"pr_spread_{_how}", sql.pagerank(_edges) + " SELECT node::BIGINT AS node, round(rank, 6) AS rank FROM r10")(
        lambda spark, sf_dir, how=_how: rounded(pr.pagerank(sample(spark) if how == "per_value" else pairs(spark, sf_dir, "g4"), spread=how).df, "rank")
    )


@add("proc_pindex_g2", _TOP + f" SELECT {sql_id('customer', 'author')} AS author, c_name AS name, round(p_index, 6) AS p_index FROM (SELECT * FROM a ORDER BY p_index DESC, author LIMIT 5) JOIN customer ON author = c_custkey")
def proc_pindex_g2(spark, sf_dir):
    """One procedure from the tables to the names: extract, rank, join with authors, order, limit, look names up."""
    found = run(optimise(parse_procedure(procedures.P_INDEX)), tables_catalog(spark, sf_dir))
    return found.df.select("author", "name", F.round(F.col("p_index").cast("double"), 6).alias("p_index"))
