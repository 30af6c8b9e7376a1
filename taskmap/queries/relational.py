"""Relational operators, scalar functions and batch twins of the streams."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap import objective as ob
from taskmap.functions.sql import register_sql
from taskmap.operators.components import components as connected
from taskmap.plans.iterate import barrier
from taskmap.queries import text as q
from taskmap.queries.steps import T32, mod
from taskmap.sources import graphs as src
from taskmap.streaming import edges as st

QUERIES: dict = {}
SQL: dict = {}


def here(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


@here("heavy_edges", f"WITH {q.graph('copurchase')} SELECT src, dst, w FROM e WHERE w >= 2 AND src < dst")
def heavy_edges(spark: SparkSession, d: str) -> DataFrame:
    return src.copurchase(spark, d).edges.filter("w >= 2 and src < dst")


@here("top_pairs", f"WITH {q.graph('copurchase')}, {q.mapping()}, {q.PLACED} SELECT pe_s AS pe_x, pe_d AS pe_y, CAST(sum(w) AS BIGINT) AS w FROM pl WHERE pe_s < pe_d GROUP BY pe_s, pe_d ORDER BY w DESC, pe_x, pe_y LIMIT 10")
def top_pairs(spark: SparkSession, d: str) -> DataFrame:
    """The ten pairs of blocks with most volume."""
    g = src.copurchase(spark, d)
    return ob.quotient(g, mod(g)).filter("pe_x < pe_y").orderBy(F.desc("w"), "pe_x", "pe_y").limit(10)


@here("top_boundary_vertices", f"WITH {q.graph('copurchase')}, {q.mapping()}, {q.PLACED} SELECT src AS id, CAST(sum(w) AS BIGINT) AS outside FROM pl WHERE pe_s <> pe_d GROUP BY src ORDER BY outside DESC, id LIMIT 10")
def top_boundary_vertices(spark: SparkSession, d: str) -> DataFrame:
    """The ten tasks with most volume to other blocks."""
    g = src.copurchase(spark, d)
    out = ob.placed(g.edges, mod(g)).filter("pe_s <> pe_d").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("outside"))
    return out.orderBy(F.desc("outside"), "id").limit(10)


ADJACENT = f"SELECT src, dst FROM (WITH {q.graph('line_adjacent')} SELECT src, dst FROM e)"


@here("edges_intersect", f"WITH {q.graph('copurchase')} SELECT src, dst FROM e INTERSECT {ADJACENT}")
def edges_intersect(spark: SparkSession, d: str) -> DataFrame:
    """Pairs that are bought together and stand on neighbouring lines."""
    return src.copurchase(spark, d).edges.select("src", "dst").intersect(src.line_adjacent(spark, d).edges.select("src", "dst"))


TRADE = "orders JOIN lineitem ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation a ON a.n_nationkey = c_nationkey JOIN nation b ON b.n_nationkey = s_nationkey"


@here("traffic_cube", f"SELECT CAST(a.n_regionkey AS INTEGER) AS from_region, CAST(b.n_regionkey AS INTEGER) AS to_region, count(*) AS w FROM {TRADE} GROUP BY CUBE(a.n_regionkey, b.n_regionkey)")
def traffic_cube(spark: SparkSession, d: str) -> DataFrame:
    """Lines between customers' and suppliers' regions, with all totals."""
    orders, lines = src.load(spark, d, "orders", "o_orderkey", "o_custkey"), src.load(spark, d, "lineitem", "l_orderkey", "l_suppkey")
    nation = src.load(spark, d, "nation", "n_nationkey", "n_regionkey")
    region = lambda key, name: F.broadcast(nation.select(F.col("n_nationkey").alias(key), F.col("n_regionkey").cast("int").alias(name)))
    customers = src.load(spark, d, "customer", "c_custkey", "c_nationkey").join(region("c_nationkey", "from_region"), "c_nationkey")
    suppliers = src.load(spark, d, "supplier", "s_suppkey", "s_nationkey").join(region("s_nationkey", "to_region"), "s_nationkey")
    own = orders.join(lines, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("c_custkey") == F.col("o_custkey")).join(suppliers, F.col("s_suppkey") == F.col("l_suppkey"))
    return own.cube("from_region", "to_region").agg(F.count("*").alias("w"))


@here("asof_handoff", "SELECT event_id, user_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS after_purchase FROM events")
def asof_handoff(spark: SparkSession, d: str) -> DataFrame:
    """Each event with its user's last purchase before it: an as-of join as a window over the user's events."""
    events = src.load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    before = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return events.select("event_id", "user_id", F.last(bought, ignorenulls=True).over(before).alias("after_purchase"))


@here("components", f"WITH RECURSIVE {q.graph('chain')}, r(id, component) AS (SELECT id, id FROM v UNION SELECT e.dst, r.component FROM r JOIN e ON e.src = r.id) SELECT id, min(component) AS component FROM r GROUP BY id")
def components(spark: SparkSession, d: str) -> DataFrame:
    return connected(src.chains(spark, d))


#: Runtime settings: after so many levels or rows (100 and a million by default) a recursive query fails.
RECURSION = ("spark.sql.cteRecursionLevelLimit", "spark.sql.cteRecursionRowLimit")


@contextmanager
def unlimited(spark: SparkSession):
    """While a recursion runs that ends by itself."""
    before = {name: spark.conf.get(name) for name in RECURSION}
    for name in RECURSION:
        spark.conf.set(name, "-1")
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)


@here("components_recursive", f"WITH RECURSIVE {q.graph('chain')}, r(id, component) AS (SELECT id, id FROM v UNION SELECT e.dst, r.component FROM r JOIN e ON e.src = r.id) SELECT id, min(component) AS component FROM r GROUP BY id")
def components_recursive(spark: SparkSession, d: str) -> DataFrame:
    """The same by a recursive query: for graphs of few and short paths."""
    g = src.chains(spark, d)
    g.vertices.createOrReplaceTempView("chain_tasks")
    g.edges.filter("src < dst").createOrReplaceTempView("chain_edges")
    least = "WITH RECURSIVE r(id, component) AS (SELECT id, id FROM chain_tasks UNION ALL SELECT e.dst, r.component FROM r JOIN chain_edges e ON e.src = r.id) SELECT id, min(component) AS component FROM r GROUP BY id"
    with unlimited(spark):
        return barrier(spark.sql(least))


@here("page_links", "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS link FROM pages")
def page_links(spark: SparkSession, d: str) -> DataFrame:
    return src.page_links(spark, d)


@here("event_props", "SELECT CAST(date_trunc('hour', ts) AS TIMESTAMP) AS hour, event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum, count(*) AS n FROM events GROUP BY 1, 2")
def event_props(spark: SparkSession, d: str) -> DataFrame:
    events = src.load(spark, d, "events", "ts", "event_type", "props")
    k = F.get_json_object("props", "$.k").cast("long")
    return events.groupBy(F.date_trunc("hour", "ts").alias("hour"), "event_type").agg(F.sum(k).alias("k_sum"), F.count("*").alias("n"))


@here("vector_cells", "SELECT vec_id, list_aggregate(list_transform(list_slice(embedding, 1, 8), lambda x: CAST(floor(CAST(x AS DOUBLE) * 4) AS BIGINT)), 'string_agg', ',') AS cell, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def vector_cells(spark: SparkSession, d: str) -> DataFrame:
    v = src.load(spark, d, "embeddings", "vec_id", "embedding")
    cell = F.transform(F.slice("embedding", 1, 8), lambda x: F.floor(x.cast("double") * 4).cast("long").cast("string"))
    return v.select("vec_id", F.array_join(cell, ",").alias("cell"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@here("sql_functions", f"WITH {q.graph('mesh')}, {q.mapping()}, {q.PLACED} SELECT CAST(sum(w * ({q.distance(T32, 'pe_s', 'pe_d')})) AS BIGINT) AS j, CAST({q.bound('(SELECT sum(c) FROM v)', 32)} AS BIGINT) AS bound, CAST(sum({q.noise('src', 'dst')}) AS BIGINT) AS noise, CAST(5 AS INTEGER) AS bucket FROM pl")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    """The objective and other functions from SQL text."""
    g = src.mesh(spark, d)
    register_sql(spark, T32, g, mod(g))
    return spark.sql(
        "SELECT sum(e.w * pe_distance(s.pe, t.pe)) AS j, load_bound((SELECT sum(c) FROM tasks), 32, 3, 100) AS bound, "
        "sum(edge_noise(e.src, e.dst, 0)) AS noise, loss_bucket(-8L) AS bucket FROM edges e JOIN mapping s ON s.id = e.src JOIN mapping t ON t.id = e.dst"
    )


@here("topology_pes", "SELECT CAST(range AS INTEGER) AS pe, CAST(range // 4 AS INTEGER) AS l1, CAST(range // 32 AS INTEGER) AS l2, CAST(range // 96 AS INTEGER) AS l3, coalesce(n, 0) AS n FROM range(96) LEFT JOIN (SELECT l_partkey % 96 AS pe, count(*) AS n FROM lineitem GROUP BY 1) ON pe = range")
def topology_pes(spark: SparkSession, d: str) -> DataFrame:
    """The table function's PEs, with the number of lines whose parts they have."""
    register_sql(spark, T32)
    lines = src.load(spark, d, "lineitem", "l_partkey")
    return spark.sql(
        "SELECT t.pe, l1, l2, l3, coalesce(n, 0L) AS n FROM topology_pes('4:8:3', '1:10:100') t "
        "LEFT JOIN (SELECT CAST(l_partkey % 96 AS INT) AS pe, count(*) AS n FROM {lines} GROUP BY 1) u ON u.pe = t.pe",
        lines=lines,
    )


def events(spark: SparkSession, d: str) -> DataFrame:
    return src.load(spark, d, "events", "event_id", "ts", "user_id")


def _windows(width: int, slide: int) -> str:
    """Starts of all windows that hold a moment, in minutes since the epoch."""
    first = f"(epoch_us(ts) // {slide * 60_000_000}) * {slide}"
    return f"SELECT *, unnest([{', '.join(f'{first} - {i * slide}' for i in range(width // slide))}]) AS begins FROM events"


def _edges(width: int, slide: int) -> str:
    n = f"n AS (SELECT begins, user_id, count(*) AS n FROM ({_windows(width, slide)}) GROUP BY begins, user_id)"
    return f"WITH {n} SELECT make_timestamp(x.begins * 60000000) AS start, x.user_id AS a, y.user_id AS b, CAST(x.n * y.n AS BIGINT) AS w FROM n x JOIN n y ON x.begins = y.begins AND x.user_id < y.user_id"


@here("window_edges_tumbling", _edges(10, 10))
def window_edges_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return st.window_edges(events(spark, d), "10 minutes")


@here("window_edges_sliding", _edges(10, 5))
def window_edges_sliding(spark: SparkSession, d: str) -> DataFrame:
    return st.window_edges(events(spark, d), "10 minutes", "5 minutes")


@here("session_counts", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 15 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def session_counts(spark: SparkSession, d: str) -> DataFrame:
    return st.session_counts(events(spark, d))
