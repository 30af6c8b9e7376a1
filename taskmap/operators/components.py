"""Connected components of a task graph by star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph
from taskmap.plans.iterate import barrier


def components(graph: TaskGraph, most_rounds: int = 60) -> DataFrame:
    """id, component: the least id that can be reached. Rounds grow with the logarithm of the longest path.

    In a round every vertex links its larger neighbours with its least one, then itself and its smaller neighbours with the
    least of these; links only move towards smaller ids, and end as stars.
    """
    links = barrier(graph.edges.filter("src > dst").select(F.col("src").alias("u"), F.col("dst").alias("v")))
    for _ in range(most_rounds):
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        new = barrier(small.filter("u <> v").distinct())
        settled = not new.join(links, ["u", "v"], "left_anti").limit(1).count() and not links.join(new, ["u", "v"], "left_anti").limit(1).count()
        links = new
        if settled:
            break
    star = links.select(F.col("u").alias("id"), F.col("v").alias("component"))
    return graph.vertices.select("id").join(star, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
