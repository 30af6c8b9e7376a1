"""Task graphs of the experiments, built from the given tables.

Each builder takes (spark, folder) and returns a TaskGraph. All edges come from equi-joins on bounded groups (the lines of
an order, the pages of a link, the points of neighbouring cells); only the columns named are read.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph, keyed


def load(spark: SparkSession, folder: str, table: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{table}.parquet")
    return df.select(*columns) if columns else df


def unit(ids: DataFrame) -> DataFrame:
    return ids.select(F.col(ids.columns[0]).cast("long").alias("id"), F.lit(1).cast("long").alias("c"))


def parts(spark: SparkSession, folder: str, weights: str = "unit") -> DataFrame:
    """Parts as vertices, with weight 1 or p_size."""
    own = load(spark, folder, "part", "p_partkey", "p_size")
    return own.select(F.col("p_partkey").cast("long").alias("id"), (F.lit(1) if weights == "unit" else F.col("p_size")).cast("long").alias("c"))


def _together(members: DataFrame, group: str, member: str) -> DataFrame:
    """a, b for members of one group, a before b. Groups are bounded (an order's lines, a filtered link's pages)."""
    left = members.select(F.col(group).alias("g"), F.col(member).alias("a"))
    right = members.select(F.col(group).alias("g"), F.col(member).alias("b"))
    return left.join(keyed(right), "g").filter("a < b").select("a", "b")


def copurchase(spark: SparkSession, folder: str, weights: str = "unit") -> TaskGraph:
    """Parts bought in one order; w is the number of such orders."""
    lines = load(spark, folder, "lineitem", "l_orderkey", "l_partkey").distinct()
    return TaskGraph.from_pairs(_together(lines, "l_orderkey", "l_partkey"), parts(spark, folder, weights))


def mesh_width(spark: SparkSession, folder: str) -> int:
    return math.isqrt(load(spark, folder, "part", "p_partkey").count())


def mesh(spark: SparkSession, folder: str, weights: str = "unit") -> TaskGraph:
    """Parts row by row on a grid, with their right, lower and diagonal neighbours: also a triangulated grid."""
    vertices = parts(spark, folder, weights)
    width = max(1, mesh_width(spark, folder))
    inner = F.col("id") % width < width - 1
    ends = F.array(F.when(inner, F.col("id") + 1), F.col("id") + width, F.when(inner, F.col("id") + width + 1))
    pairs = vertices.select(F.col("id").alias("a"), F.explode(ends).alias("b")).filter("b is not null")
    known = vertices.select(F.col("id").alias("b"))
    return TaskGraph.from_pairs(pairs.join(keyed(known), "b", "left_semi"), vertices)


def line_adjacent(spark: SparkSession, folder: str) -> TaskGraph:
    """Parts of consecutive lines of an order, in a total order of the lines."""
    order = ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]
    lines = load(spark, folder, "lineitem", "l_orderkey", *order)
    following = F.lead("l_partkey").over(W.partitionBy("l_orderkey").orderBy(*order))
    pairs = lines.select(F.col("l_partkey").alias("a"), following.alias("b")).filter("b is not null")
    return TaskGraph.from_pairs(pairs, parts(spark, folder))


def chains(spark: SparkSession, folder: str) -> TaskGraph:
    """Consecutive turns of a conversation: disconnected paths."""
    turns = load(spark, folder, "conversations", "conv_id", "turn").select((F.col("conv_id") * 16 + F.col("turn")).cast("long").alias("id"), "conv_id", "turn").distinct()
    following = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("id").alias("b"))
    return TaskGraph.from_pairs(turns.join(following, ["conv_id", "turn"]).select(F.col("id").alias("a"), "b"), unit(turns.select("id")))


LINK = r'href="([^"]+)"'


def page_links(spark: SparkSession, folder: str) -> DataFrame:
    """page_id, link: the distinct link targets of each page."""
    pages = load(spark, folder, "pages", "page_id", "html")
    return pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit(LINK), F.lit(1)))).alias("link"))


def colink(spark: SparkSession, folder: str, least: int = 2, most: int = 50) -> TaskGraph:
    """Pages that share a link target which stands on least to most pages."""
    links = page_links(spark, folder)
    usual = links.groupBy("link").count().filter(F.col("count").between(least, most)).select("link")
    return TaskGraph.from_pairs(_together(links.join(usual, "link"), "link", "page_id"), unit(load(spark, folder, "pages", "page_id")))


def unit_square(spark: SparkSession, folder: str) -> DataFrame:
    """id, x, y: the first two coordinates of the embeddings, scaled to the unit square."""
    v = load(spark, folder, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    ends = v.agg(*[f(c).alias(f"{n}_{c}") for c in "xy" for n, f in (("low", F.min), ("high", F.max))])
    scaled = lambda c: ((F.col(c) - F.col(f"low_{c}")) / (F.col(f"high_{c}") - F.col(f"low_{c}"))).alias(c)
    return v.join(F.broadcast(ends)).select("id", scaled("x"), scaled("y"))


def geometric_radius(n: int) -> float:
    return 0.55 * math.sqrt(math.log(n) / n) if n > 1 else 1.0


def near_points(points: DataFrame, radius: float) -> DataFrame:
    """a, b for points nearer than radius: a range join as an equi-join on cells as wide as the radius."""
    cell = lambda c: F.floor(F.col(c) / F.lit(radius)).cast("long")
    own = points.select("id", "x", "y", cell("x").alias("cx"), cell("y").alias("cy"))
    around = F.explode(F.expr("flatten(transform(sequence(-1, 1), i -> transform(sequence(-1, 1), j -> struct(cx + i as cx, cy + j as cy))))")).alias("cell")
    reach = own.select(F.col("id").alias("b"), F.col("x").alias("x2"), F.col("y").alias("y2"), around).select("b", "x2", "y2", "cell.cx", "cell.cy")
    near = (F.col("x") - F.col("x2")) * (F.col("x") - F.col("x2")) + (F.col("y") - F.col("y2")) * (F.col("y") - F.col("y2"))
    return own.join(reach, ["cx", "cy"]).filter(F.col("id") < F.col("b")).filter(near < F.lit(radius * radius)).select(F.col("id").alias("a"), "b")


def geometric(spark: SparkSession, folder: str) -> TaskGraph:
    """Random points in the unit square, linked within the published radius."""
    points = unit_square(spark, folder)
    return TaskGraph.from_pairs(near_points(points, geometric_radius(points.count())), unit(points.select("id")))


def coship(spark: SparkSession, folder: str) -> TaskGraph:
    """Suppliers of one order."""
    lines = load(spark, folder, "lineitem", "l_orderkey", "l_suppkey").distinct()
    return TaskGraph.from_pairs(_together(lines, "l_orderkey", "l_suppkey"), unit(load(spark, folder, "supplier", "s_suppkey")))


def trade(spark: SparkSession, folder: str) -> TaskGraph:
    """Customers (even ids) and suppliers (odd ids); w is the number of lines."""
    orders = load(spark, folder, "orders", "o_orderkey", "o_custkey")
    lines = load(spark, folder, "lineitem", "l_orderkey", "l_suppkey")
    pairs = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select((F.col("o_custkey") * 2).alias("a"), (F.col("l_suppkey") * 2 + 1).alias("b"))
    return TaskGraph.from_pairs(pairs)


def handoff_pairs(events: DataFrame) -> DataFrame:
    """a, b: the users of consecutive events in the order of (ts, event_id).

    Days are ordered within themselves; the last event of a day meets the first of the next day that has any in a table of
    one row for each day, so no window spans all events.
    """
    order = ["ts", "event_id"]
    own = events.select("ts", "event_id", "user_id", F.to_date("ts").alias("day"))
    within = own.select(F.col("user_id").alias("a"), F.lead("user_id").over(W.partitionBy("day").orderBy(*order)).alias("b")).filter("b is not null")
    key = F.struct(*order)
    days = own.groupBy("day").agg(F.max_by("user_id", key).alias("a"), F.min_by("user_id", key).alias("first"))
    across = days.select("a", F.lead("first").over(W.orderBy("day")).alias("b")).filter("b is not null")
    return within.unionByName(across)


def handoff(spark: SparkSession, folder: str) -> TaskGraph:
    """Users of consecutive events: volumes with a direction, made symmetric; hand-offs to oneself dropped."""
    events = load(spark, folder, "events", "ts", "event_id", "user_id")
    return TaskGraph.from_pairs(handoff_pairs(events), unit(events.select("user_id").distinct()))


def overlap(spark: SparkSession, folder: str, least: int = 2, most: int = 20) -> TaskGraph:
    """Documents that share words which least to most documents have; w is the number of such words."""
    docs = load(spark, folder, "documents", "doc_id", "text")
    words = docs.select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("word")).filter("word <> ''")
    usual = words.groupBy("word").count().filter(F.col("count").between(least, most)).select("word")
    return TaskGraph.from_pairs(_together(words.join(usual, "word"), "word", "doc_id"), unit(docs.select("doc_id")))


BUILDERS = {
    "copurchase": copurchase,
    "mesh": mesh,
    "line_adjacent": line_adjacent,
    "chain": chains,
    "colink": colink,
    "geometric": geometric,
    "coship": coship,
    "trade": trade,
    "handoff": handoff,
    "overlap": overlap,
}


def trivial_mapping(vertices: DataFrame, k: int, kind: str = "mod", seed: int = 0) -> DataFrame:
    """id, pe without looking at edges: by id modulo k, by contiguous ranges of ids, or by a seeded hash."""
    if kind == "mod":
        return vertices.select("id", (F.col("id") % k).cast("int").alias("pe"))
    if kind == "range":
        n = vertices.count()
        return vertices.select("id", F.call_function("div", F.col("id") * k, F.lit(max(1, n)).cast("long")).cast("int").alias("pe"))
    if kind == "hash":
        from taskmap.operators.matching import edge_noise

        return vertices.select("id", (edge_noise(F.col("id"), F.col("id"), seed) % k).cast("int").alias("pe"))
    raise ValueError(f"unknown kind of mapping: {kind}")
