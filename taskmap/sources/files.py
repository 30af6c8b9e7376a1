"""Graphs and mappings in files and tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.graph import TaskGraph


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", weighted: bool = True) -> TaskGraph:
    """Lines "a b [w]", one for each undirected edge, in any direction; lines that start with # are comments."""
    schema = "a long, b long" + (", w long" if weighted else "")
    return TaskGraph.from_pairs(spark.read.csv(path, schema=schema, sep=sep, comment="#"))


def read_adjacency_text(spark: SparkSession, path: str) -> TaskGraph:
    """Partitioning archives' format: a header "n m [fmt]", then line i lists the neighbours of vertex i, from 1.

    fmt 1: each neighbour is followed by the edge's weight; 10: the line begins with the vertex's weight; 11: both. Files
    are read whole by one task each, which keeps the lines' numbers; ids become 0, 1, ...
    """
    lines = spark.read.text(path, wholetext=True).select(F.filter(F.split("value", "\n"), lambda x: ~x.startswith("%")).alias("l"))
    head = F.split(F.trim(F.col("l")[0]), r"\s+")
    told = lines.select(F.when(F.size(head) > 2, F.lpad(head[2], 3, "0")).otherwise(F.lit("000")).alias("fmt"), head[0].cast("int").alias("n"), F.posexplode(F.slice("l", 2, head[0].cast("int"))).alias("i", "line"))
    numbers = told.select("fmt", F.col("i").cast("long").alias("id"), F.transform(F.filter(F.split("line", r"\s+"), lambda x: x != ""), lambda x: x.cast("long")).alias("x"))
    has_c, has_w = F.substring("fmt", 2, 1) == "1", F.substring("fmt", 3, 1) == "1"
    vertices = numbers.select("id", F.when(has_c, F.col("x")[0]).otherwise(F.lit(1)).cast("long").alias("c"))
    rest = F.when(has_c, F.slice("x", 2, F.greatest(F.size("x") - 1, F.lit(0)))).otherwise(F.col("x"))
    some = numbers.select("id", has_w.alias("has_w"), rest.alias("x"))
    pairs = some.select("id", "has_w", F.posexplode("x").alias("j", "v"), "x").filter(~F.col("has_w") | (F.col("j") % 2 == 0))
    pairs = pairs.select("id", (F.col("v") - 1).alias("b"), F.when(F.col("has_w"), F.expr("try_element_at(x, j + 2)")).otherwise(F.lit(1)).alias("w"))
    # each edge stands in both lines: one direction is enough
    return TaskGraph.from_pairs(pairs.filter("id < b").select(F.col("id").alias("a"), "b", "w"), vertices)


def save_bucketed(graph: TaskGraph, name: str, buckets: int) -> TaskGraph:
    """Tables bucketed and sorted by vertex: joins on src and on id then need no exchange on the large side."""
    spark = graph.edges.sparkSession
    graph.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(f"{name}_edges")
    graph.vertices.write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(f"{name}_vertices")
    return TaskGraph(spark.table(f"{name}_vertices"), spark.table(f"{name}_edges"))


def write_mapping(mapping: DataFrame, path: str, by_pe: bool = True) -> None:
    """Parquet, a folder for each PE if by_pe, so that a PE reads only its own tasks."""
    writer = mapping.write.mode("overwrite")
    (writer.partitionBy("pe") if by_pe else writer).parquet(path)


def append_runs(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").parquet(path)
