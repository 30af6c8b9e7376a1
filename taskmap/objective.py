"""What a mapping costs and how it is balanced, and what single moves would change."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph, keyed
from taskmap.topology import MatrixTopology, Topology, load_bound_column, with_distance


def placed(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """Edges with the PEs of both ends: src, dst, w, pe_s, pe_d."""
    s = mapping.select(F.col("id").alias("src"), F.col("pe").alias("pe_s"))
    t = mapping.select(F.col("id").alias("dst"), F.col("pe").alias("pe_d"))
    return edges.join(keyed(s), "src").join(keyed(t), "dst")


def total(c: str | Column) -> Column:
    return F.coalesce(F.sum(c), F.lit(0)).cast("long")


def objective(graph: TaskGraph, mapping: DataFrame, topology: Topology | MatrixTopology) -> DataFrame:
    """j: volume times cost factor over all ordered pairs, so an undirected edge counts twice."""
    own = with_distance(placed(graph.edges, mapping), topology, "pe_s", "pe_d")
    return own.agg(total(F.col("w") * F.col("d")).alias("j"))


def edge_cut(graph: TaskGraph, mapping: DataFrame) -> DataFrame:
    """cut: volume of the undirected edges between blocks."""
    return placed(graph.edges.filter("src < dst"), mapping).filter("pe_s <> pe_d").agg(total("w").alias("cut"))


def quotient(graph: TaskGraph, mapping: DataFrame) -> DataFrame:
    """pe_x, pe_y, w: the volume between blocks, both directions."""
    own = placed(graph.edges, mapping).filter("pe_s <> pe_d")
    return own.groupBy(F.col("pe_s").alias("pe_x"), F.col("pe_d").alias("pe_y")).agg(F.sum("w").alias("w"))


def quotient_pivot(graph: TaskGraph, mapping: DataFrame, k: int) -> DataFrame:
    """pe_x and a column to_<pe> for each of k blocks."""
    wide = quotient(graph, mapping).groupBy("pe_x").pivot("pe_y", list(range(k))).agg(F.sum("w"))
    return wide.select("pe_x", *[F.coalesce(F.col(f"`{y}`"), F.lit(0)).cast("long").alias(f"to_{y}") for y in range(k)])


def objective_by_level(graph: TaskGraph, mapping: DataFrame, topology: Topology) -> DataFrame:
    """level (null: all), w, cost: at which level of the machine the volume is paid."""
    own = placed(graph.edges, mapping).select(topology.level("pe_s", "pe_d").alias("level"), "w", (F.col("w") * topology.distance("pe_s", "pe_d")).alias("x"))
    return own.rollup("level").agg(F.sum("w").alias("w"), F.sum("x").alias("cost"))


def block_loads(vertices: DataFrame, mapping: DataFrame, k: int, eps_num: int, eps_den: int) -> DataFrame:
    """pe, weight, overloaded for each of k PEs, empty ones included."""
    spark = vertices.sparkSession
    loads = vertices.join(keyed(mapping), "id").groupBy("pe").agg(F.sum("c").alias("weight"))
    every = spark.range(k).select(F.col("id").cast("int").alias("pe"))
    own = every.join(F.broadcast(loads), "pe", "left").select("pe", F.coalesce("weight", F.lit(0)).cast("long").alias("weight"))
    c_total = vertices.agg(total("c").alias("c_total"))
    bound = load_bound_column(F.col("c_total"), F.lit(k).cast("long"), eps_num, eps_den)
    return own.join(F.broadcast(c_total)).select("pe", "weight", (F.col("weight") > bound).alias("overloaded"))


def imbalance(vertices: DataFrame, mapping: DataFrame, k: int) -> DataFrame:
    """max_block, imbalance: the heaviest block, and how far it is above the average."""
    loads = vertices.join(keyed(mapping), "id").groupBy("pe").agg(F.sum("c").alias("weight"))
    own = loads.agg(F.coalesce(F.max("weight"), F.lit(0)).cast("long").alias("max_block"), total("weight").alias("all"))
    return own.select("max_block", F.round(F.lit(k) * F.col("max_block") / F.col("all") - 1, 6).alias("imbalance"))


def connectivity(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """id, pe, w: the volume from each vertex into each block it touches, its own included."""
    t = mapping.select(F.col("id").alias("dst"), "pe")
    return edges.join(keyed(t), "dst").groupBy(F.col("src").alias("id"), "pe").agg(F.sum("w").alias("w"))


def connectivity_map(conn: DataFrame) -> DataFrame:
    """id, blocks: the same, packed as a map of at most min(degree, k) entries."""
    return conn.groupBy("id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("pe", "w")))).alias("blocks"))


def costs(conn: DataFrame, candidates: DataFrame, topology: Topology | MatrixTopology) -> DataFrame:
    """candidates(id, pe_new) with cost: what the vertex's volume would cost from that PE.

    In a tree, with S_i the volume into the PE's component at level i, the cost is the sum of d_i (S_i - S_{i-1}): l grouped
    sums instead of all pairs of a vertex's blocks. For a general matrix the vertex's blocks are paired.
    """
    if isinstance(topology, MatrixTopology):
        both = candidates.join(keyed(conn), "id").withColumnRenamed("pe", "pe_at")
        own = topology.lookup(both, "pe_new", "pe_at")
        return own.groupBy("id", "pe_new").agg(F.sum(F.col("w") * F.col("d")).alias("cost"))
    out = candidates.join(keyed(conn.select("id", F.col("pe").alias("pe_new"), F.col("w").alias("s0"))), ["id", "pe_new"], "left")
    for i in range(1, len(topology.arity) + 1):
        level = conn.groupBy("id", topology.component("pe", i).alias(f"x{i}")).agg(F.sum("w").alias(f"s{i}"))
        out = out.withColumn(f"x{i}", topology.component("pe_new", i)).join(keyed(level), ["id", f"x{i}"], "left")
    s = [F.coalesce(F.col(f"s{i}"), F.lit(0)) for i in range(len(topology.arity) + 1)]
    cost = sum((F.lit(d) * (s[i + 1] - s[i]) for i, d in enumerate(topology.distances)), F.lit(0))
    return out.select("id", "pe_new", cost.cast("long").alias("cost"))


def gains(conn: DataFrame, mapping: DataFrame, topology: Topology | MatrixTopology, candidates: DataFrame | None = None) -> DataFrame:
    """id, pe_old, pe_new, gain for each vertex and neighbouring block but its own (or for the candidates given).

    A move lowers the undirected cost by its gain, so J by twice that.
    """
    own = keyed(mapping.select("id", F.col("pe").alias("pe_old")))
    if candidates is None:
        candidates = conn.join(own, "id").filter("pe <> pe_old").select("id", F.col("pe").alias("pe_new"))
    stay = own.join(keyed(candidates.select("id").distinct()), "id", "left_semi").select("id", F.col("pe_old").alias("pe_new"))
    every = costs(conn, candidates.select("id", "pe_new").unionByName(stay), topology)
    now = F.max(F.when(F.col("pe_new") == F.col("pe_old"), F.col("cost"))).over(W.partitionBy("id"))
    both = every.join(own, "id").withColumn("now", now)
    return both.filter("pe_new <> pe_old").select("id", "pe_old", "pe_new", (F.col("now") - F.col("cost")).alias("gain"))


def cut_gains(conn: DataFrame, mapping: DataFrame, candidates: DataFrame | None = None) -> DataFrame:
    """id, pe_old, pe_new, gain by edge-cut: the volume into the new block less that into the own one."""
    own = keyed(mapping.select("id", F.col("pe").alias("pe_old")))
    inside = conn.join(own, "id").filter("pe = pe_old").select("id", F.col("w").alias("inside"))
    if candidates is None:
        reach = conn.join(own, "id").filter("pe <> pe_old").select("id", "pe_old", F.col("pe").alias("pe_new"), "w")
    else:
        touch = conn.select("id", F.col("pe").alias("pe_new"), "w")
        reach = candidates.select("id", "pe_new").join(own, "id").join(keyed(touch), ["id", "pe_new"], "left")
    out = reach.join(keyed(inside), "id", "left")
    return out.select("id", "pe_old", "pe_new", (F.coalesce("w", F.lit(0)) - F.coalesce("inside", F.lit(0))).cast("long").alias("gain"))
