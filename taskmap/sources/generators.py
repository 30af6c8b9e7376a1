"""Synthetic graphs of any size, made in parallel from ranges."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph
from taskmap.sources.graphs import geometric_radius, near_points, unit


def grid(spark: SparkSession, rows: int, columns: int, diagonal: bool = False) -> TaskGraph:
    """A grid with unit weights; with diagonals it is a triangulation."""
    v = spark.range(rows * columns)
    right = F.when(F.col("id") % columns < columns - 1, F.col("id") + 1)
    down = F.when(F.col("id") < (rows - 1) * columns, F.col("id") + columns)
    ends = [right, down] + ([F.when(right.isNotNull() & down.isNotNull(), F.col("id") + columns + 1)] if diagonal else [])
    pairs = v.select(F.col("id").alias("a"), F.explode(F.array(*ends)).alias("b")).filter("b is not null")
    return TaskGraph.from_pairs(pairs, unit(v))


def geometric(spark: SparkSession, n: int, seed: int = 0) -> TaskGraph:
    """n points in the unit square (coordinates from a hash of id and seed), linked within the published radius."""
    place = lambda salt: (F.pmod(F.xxhash64("id", F.lit(seed), F.lit(salt)), F.lit(1 << 40)) / F.lit(float(1 << 40)))
    points = spark.range(n).select("id", place(1).alias("x"), place(2).alias("y"))
    return TaskGraph.from_pairs(near_points(points, geometric_radius(n)), unit(spark.range(n)))
