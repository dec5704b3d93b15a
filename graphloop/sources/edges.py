"""Edge views over the given tables: columns src and dst, some with a weight."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphloop.materialize import durable, settings
from graphloop.relation import TooLarge
from graphloop.terms import node_id, sql_id

BRAND = "Brand#7"
PAIR_LIMIT = 200_000_000


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def nation_lanes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G1: for each customer nation the two foreign supplier nations with the most revenue; weight 1 or 2."""
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))
    order = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer = read(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src"))
    supplier = read(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst"))
    flow = (
        line.join(order, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(customer, F.col("o_custkey") == F.col("c_custkey"))
        .join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        .where("src <> dst")
        .groupBy("src", "dst")
        .agg(F.sum("revenue").alias("revenue"))
    )
    best = Window.partitionBy("src").orderBy(F.col("revenue").desc(), "dst")
    return flow.withColumn("position", F.row_number().over(best)).where("position <= 2").select("src", "dst", F.col("position").cast("double").alias("weight"))


def _dated_parts(spark: SparkSession, sf_dir: str, brand: str | None) -> DataFrame:
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    if brand is not None:
        part = read(spark, sf_dir, "part").where(F.col("p_brand") == brand).select("p_partkey")
        line = line.join(part, F.col("l_partkey") == F.col("p_partkey"), "left_semi")
    order = read(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").alias("date"))
    return line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).select("l_partkey", "l_orderkey", "date").distinct()


def brand_citation(spark: SparkSession, sf_dir: str, brand: str = BRAND) -> DataFrame:
    """G2: an order cites every older order that shares a part of the brand; weight is days + 1.

    The pairs of a part grow with the square of its orders, so their number is computed first
    and a topic with more than ``PAIR_LIMIT`` is refused.
    """
    rows = _dated_parts(spark, sf_dir, brand)
    pairs = rows.groupBy("l_partkey").count().agg(F.sum(F.col("count") * F.col("count"))).first()[0] or 0
    if pairs > PAIR_LIMIT:
        raise TooLarge(f"{pairs} pairs of orders share a part; narrow the topic")
    old = rows.select("l_partkey", F.col("l_orderkey").alias("dst"), F.col("date").alias("old_date"))
    found = rows.join(old, "l_partkey").where(F.col("old_date") < F.col("date"))
    days = (F.datediff("date", "old_date") + 1).cast("double")
    return found.select(F.col("l_orderkey").alias("src"), "dst", days.alias("weight")).distinct()


def membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G3: user to group of purchases of at least 75."""
    event = read(spark, sf_dir, "events").where("event_type = 'purchase' and value >= 75")
    group = F.get_json_object("props", "$.k").cast("long")
    return event.select(node_id("user", F.col("user_id")).alias("src"), node_id("group", group).alias("dst")).distinct()


def reply_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G4: each turn to the one before in its conversation."""
    turns = read(spark, sf_dir, "conversations").select("conv_id", "turn")
    before = turns.select("conv_id", (F.col("turn") + 1).alias("turn"))
    key = F.col("conv_id") * 1000 + F.col("turn")
    return turns.join(before, ["conv_id", "turn"]).select(key.alias("src"), (key - 1).alias("dst")).distinct()


def event_lineage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G5: view and click events to their previous one of the same user and of the same group, if under six hours; weight in hours."""
    event = read(spark, sf_dir, "events").where("event_type in ('view', 'click')")
    event = event.select("event_id", "ts", "user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    found = []
    for owner in ("user_id", "k"):
        order = Window.partitionBy(owner).orderBy("ts", "event_id")
        parent = event.select("event_id", "ts", F.lag(F.struct("event_id", "ts")).over(order).alias("parent"))
        recent = parent.where(F.col("ts") < F.col("parent.ts") + F.expr("interval 6 hours"))
        hours = F.timestamp_diff("SECOND", F.col("parent.ts"), F.col("ts")) / 3600.0
        found.append(recent.select(F.col("event_id").alias("src"), F.col("parent.event_id").alias("dst"), hours.cast("double").alias("weight")))
    return found[0].union(found[1]).distinct()


def returned_supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G6: supplier to part of returned lines of 25 or more, brands 7 and 8."""
    line = read(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity >= 25").select("l_suppkey", "l_partkey")
    part = read(spark, sf_dir, "part").where(F.col("p_brand").isin("Brand#7", "Brand#8")).select("p_partkey")
    kept = line.join(part, F.col("l_partkey") == F.col("p_partkey"), "left_semi")
    return kept.select(node_id("supplier", F.col("l_suppkey")).alias("src"), node_id("part", F.col("l_partkey")).alias("dst")).distinct()


def previous_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G7: for every part each order to the one just before it by date and key; weight is days + 1."""
    rows = _dated_parts(spark, sf_dir, None)
    order = Window.partitionBy("l_partkey").orderBy("date", "l_orderkey")
    linked = rows.select(F.col("l_orderkey").alias("src"), "date", F.lag(F.struct("l_orderkey", "date")).over(order).alias("before")).where("before is not null")
    days = (F.datediff("date", "before.date") + 1).cast("double")
    return linked.select("src", F.col("before.l_orderkey").alias("dst"), days.alias("weight")).distinct()


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G8: page to each link target in its HTML; targets are strings."""
    page = read(spark, sf_dir, "pages").select("page_id", "html")
    links = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))))
    return page.select(F.col("page_id").alias("src"), links.alias("dst"))


def _blocks(vectors: DataFrame, rows: int) -> DataFrame:
    """(block, ids, missing, x): vectors (vec_id, x) in blocks of about ``rows``; x has their coordinates one after the other."""
    parts = max(-(-vectors.count() // rows), 1)
    one = F.struct("vec_id", "x")
    blocks = vectors.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(parts)).alias("block")).agg(F.collect_list(one).alias("rows"))
    missing = F.transform("rows.x", lambda x: x.isNull() | F.exists(x, lambda y: y.isNull()))
    known = F.filter("rows.x", lambda x: x.isNotNull() & ~F.exists(x, lambda y: y.isNull()))
    return durable(blocks.select("block", F.col("rows.vec_id").alias("ids"), missing.alias("missing"), F.flatten(known).alias("x")).repartition(min(parts, 32), "block"))


def _unpacked(batch: pa.RecordBatch, row: int, side: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, whether a vector is missing, matrix with rows of zeros for these) of one side of a pair of blocks."""
    ids, missing, flat = (batch.column(f"{side}_{name}")[row].values.to_numpy(zero_copy_only=False) for name in ("ids", "missing", "x"))
    known = len(ids) - int(missing.sum())
    x = np.zeros((len(ids), len(flat) // known if known else 0))
    x[~missing] = flat.reshape(known, -1)
    return ids, missing.astype(bool), x


def _nearest_in(asked: tuple, held: tuple, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(src, dst, cosine, whether there is one) of the ``k`` nearest in one block of each vector of another.

    A product of matrices leaves out what is clearly farther than the k-th nearest. The rest is summed coordinate by
    coordinate, as SQL does, so equal cosines tie. A cosine that is no number counts as the greatest, none as the least.
    """
    (a_ids, a_none, a), (b_ids, b_none, b) = asked, held
    width = max(a.shape[1], b.shape[1])
    a, b = (np.zeros((len(x), width)) if none.all() else x for x, none in ((a, a_none), (b, b_none)))
    if a.shape[1] != b.shape[1]:
        raise ValueError("vectors of different lengths")

    def norm(x):
        total = np.zeros(len(x))
        for d in range(width):
            total += x[:, d] * x[:, d]
        return np.sqrt(total)

    with np.errstate(all="ignore"):
        an, bn = norm(a), norm(b)
        near = (a / an[:, None]) @ (b / bn[:, None]).T
        near[~np.isfinite(near)] = np.inf
        near[a_none, :] = -np.inf
        near[:, b_none] = -np.inf
        itself = a_ids[:, None] == b_ids[None, :]
        near[itself] = -np.inf
        least = np.partition(near, -k, axis=1)[:, -k] if near.shape[1] > k else np.full(len(a), -np.inf)
        row, col = np.nonzero((near >= (least - 1e-9)[:, None]) & ~itself)
        dot = np.zeros(len(row))
        for d in range(width):
            dot += a[row, d] * b[col, d]
        cosine = dot / (an[row] * bn[col])
    none = a_none[row] | b_none[col]
    place = np.where(none, -np.inf, np.where(np.isnan(cosine), np.inf, cosine))
    order = np.lexsort((b_ids[col], -place, row))
    row, col, cosine, none = row[order], col[order], cosine[order], none[order]
    starts = np.searchsorted(row, row)
    best = np.arange(len(row)) - starts < k
    return a_ids[row[best]], b_ids[col[best]], cosine[best], ~none[best]


def nearest_vectors(spark: SparkSession, sf_dir: str, k: int = 5, queries: DataFrame | None = None, block: int = 1024) -> DataFrame:
    """G9: each vector to its ``k`` nearest by cosine, ties to the smaller id; weight is the cosine.

    ``queries`` (vec_id, embedding) are asked if given, else all vectors. Every pair is compared, block by block; of two
    blocks only the ``k`` nearest of each vector go on, so groups of copies add no rows.
    """
    as_double = F.transform("embedding", lambda x: x.cast("double")).alias("x")
    held = _blocks(read(spark, sf_dir, "embeddings").select("vec_id", as_double), block)
    asked = held if queries is None else _blocks(queries.select("vec_id", as_double), block)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                src, dst, cosine, some = _nearest_in(_unpacked(batch, row, "a"), _unpacked(batch, row, "b"), k)
                weight = pa.array(cosine, mask=~some)
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), weight], names=["src", "dst", "weight"])

    sides = [df.select(*(F.col(c).alias(f"{side}_{c}") for c in ("ids", "missing", "x"))) for df, side in ((asked, "a"), (held, "b"))]
    best = Window.partitionBy("src").orderBy(F.col("weight").desc(), "dst")
    with settings(spark, {"spark.sql.execution.arrow.maxRecordsPerBatch": "16"}):  # a row is two blocks
        found = durable(sides[0].crossJoin(sides[1]).mapInArrow(compare, "src long, dst long, weight double"))
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def containment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """G10: foreign keys as edges between tagged nodes; a line is known by its position in the file order of its columns."""
    nation = read(spark, sf_dir, "nation")
    customer, supplier = read(spark, sf_dir, "customer"), read(spark, sf_dir, "supplier")
    order, line = read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem")
    parts = [
        nation.select(node_id("nation", F.col("n_nationkey")).alias("src"), node_id("region", F.col("n_regionkey")).alias("dst")),
        customer.select(node_id("customer", F.col("c_custkey")), node_id("nation", F.col("c_nationkey"))),
        supplier.select(node_id("supplier", F.col("s_suppkey")), node_id("nation", F.col("s_nationkey"))),
        order.select(node_id("order", F.col("o_orderkey")), node_id("customer", F.col("o_custkey"))),
        line.select(node_id("order", F.col("l_orderkey")), node_id("part", F.col("l_partkey"))),
        line.select(node_id("order", F.col("l_orderkey")), node_id("supplier", F.col("l_suppkey"))),
    ]
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return out.distinct()


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "g1": nation_lanes,
    "g2": brand_citation,
    "g3": membership,
    "g4": reply_chain,
    "g5": event_lineage,
    "g6": returned_supply,
    "g7": previous_order,
    "g8": page_links,
    "g9": nearest_vectors,
    "g10": containment,
}

_DATED = """SELECT DISTINCT l_partkey, l_orderkey, o_orderdate AS d FROM lineitem JOIN orders ON l_orderkey = o_orderkey"""
SQL = {
    "g1": """SELECT src::BIGINT AS src, dst::BIGINT AS dst, position::DOUBLE AS weight FROM (
      SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY revenue DESC, dst) AS position FROM (
        SELECT c_nationkey AS src, s_nationkey AS dst, sum(l_extendedprice * (1 - l_discount)) AS revenue
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
        WHERE c_nationkey <> s_nationkey GROUP BY ALL)) WHERE position <= 2""",
    "g2": f"""SELECT DISTINCT a.l_orderkey AS src, b.l_orderkey AS dst, (date_diff('day', b.d, a.d) + 1)::DOUBLE AS weight
      FROM ({_DATED} JOIN part ON l_partkey = p_partkey WHERE p_brand = '{BRAND}') a
      JOIN ({_DATED} JOIN part ON l_partkey = p_partkey WHERE p_brand = '{BRAND}') b ON a.l_partkey = b.l_partkey AND b.d < a.d""",
    "g3": f"""SELECT DISTINCT {sql_id('user', 'user_id')} AS src, {sql_id('group', "(props->>'k')::BIGINT")} AS dst
      FROM events WHERE event_type = 'purchase' AND value >= 75""",
    "g4": """SELECT DISTINCT a.conv_id * 1000 + a.turn AS src, a.conv_id * 1000 + b.turn AS dst
      FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn - 1""",
    "g5": """WITH e AS (SELECT event_id, ts, user_id, (props->>'k')::BIGINT AS k FROM events WHERE event_type IN ('view', 'click')),
      p AS (SELECT event_id, ts, lag(event_id) OVER w AS pe, lag(ts) OVER w AS pt FROM e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)
        UNION ALL SELECT event_id, ts, lag(event_id) OVER w, lag(ts) OVER w FROM e WINDOW w AS (PARTITION BY k ORDER BY ts, event_id))
      SELECT DISTINCT event_id AS src, pe AS dst, (date_sub('second', pt, ts) / 3600.0)::DOUBLE AS weight FROM p WHERE ts < pt + INTERVAL 6 HOUR""",
    "g6": f"""SELECT DISTINCT {sql_id('supplier', 'l_suppkey')} AS src, {sql_id('part', 'l_partkey')} AS dst FROM lineitem JOIN part ON l_partkey = p_partkey
      WHERE l_returnflag = 'R' AND l_quantity >= 25 AND p_brand IN ('Brand#7', 'Brand#8')""",
    "g7": f"""SELECT DISTINCT l_orderkey AS src, before AS dst, (date_diff('day', bd, d) + 1)::DOUBLE AS weight FROM (
      SELECT l_orderkey, d, lag(l_orderkey) OVER w AS before, lag(d) OVER w AS bd FROM ({_DATED}) WINDOW w AS (PARTITION BY l_partkey ORDER BY d, l_orderkey))
      WHERE before IS NOT NULL""",
    "g8": """SELECT DISTINCT page_id AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages""",
    "g10": f"""SELECT {sql_id('nation', 'n_nationkey')} AS src, {sql_id('region', 'n_regionkey')} AS dst FROM nation
      UNION SELECT {sql_id('customer', 'c_custkey')}, {sql_id('nation', 'c_nationkey')} FROM customer
      UNION SELECT {sql_id('supplier', 's_suppkey')}, {sql_id('nation', 's_nationkey')} FROM supplier
      UNION SELECT {sql_id('order', 'o_orderkey')}, {sql_id('customer', 'o_custkey')} FROM orders
      UNION SELECT {sql_id('order', 'l_orderkey')}, {sql_id('part', 'l_partkey')} FROM lineitem
      UNION SELECT {sql_id('order', 'l_orderkey')}, {sql_id('supplier', 'l_suppkey')} FROM lineitem""",
}
