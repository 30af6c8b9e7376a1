"""Contracting matched or clustered vertices, and taking the contraction back."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph, keyed, project


def completed(vertices: DataFrame, matched: DataFrame) -> DataFrame:
    """id, coarse_id for every vertex: unmatched ones stand for themselves."""
    return vertices.select("id").join(keyed(matched), "id", "left").select("id", F.coalesce("coarse_id", "id").alias("coarse_id"))


def coarse_vertices(vertices: DataFrame, projection: DataFrame) -> DataFrame:
    return vertices.join(keyed(projection), "id").groupBy(F.col("coarse_id").alias("id")).agg(F.sum("c").alias("c"))


def coarse_edges(edges: DataFrame, projection: DataFrame) -> DataFrame:
    """Edges within a coarse vertex vanish, parallel ones are summed: a hash aggregation with partial sums."""
    s = projection.select(F.col("id").alias("src"), F.col("coarse_id").alias("a"))
    t = projection.select(F.col("id").alias("dst"), F.col("coarse_id").alias("b"))
    own = edges.join(keyed(s), "src").join(keyed(t), "dst").filter("a <> b")
    return own.groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("w").alias("w"))


def contract(graph: TaskGraph, projection: DataFrame) -> TaskGraph:
    return TaskGraph(coarse_vertices(graph.vertices, projection), coarse_edges(graph.edges, projection))


def coarse_degree_bound(graph: TaskGraph, projection: DataFrame) -> DataFrame:
    """coarse_id, bound: members' degrees summed up, which no coarse degree passes; a hint for skew."""
    own = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))
    return projection.join(keyed(own), "id", "left").groupBy("coarse_id").agg(F.sum(F.coalesce("deg", F.lit(0))).alias("bound"))


def uncontract(mapping: DataFrame, projection: DataFrame) -> DataFrame:
    return project(mapping, projection)
