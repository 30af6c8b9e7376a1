"""Task graphs: one row for each task, one row for each direction of each communicating pair."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VERTICES = "id long, c long"
EDGES = "src long, dst long, w long"
MAPPING = "id long, pe int"


@dataclass(frozen=True)
class TaskGraph:
    """vertices(id, c), edges(src, dst, w). Both directions of an edge are rows, so a scan is parallel over edges, and an
    aggregation by src is parallel over tasks; neighbour lists are never collected."""

    vertices: DataFrame
    edges: DataFrame

    @classmethod
    def from_pairs(cls, pairs: DataFrame, vertices: DataFrame | None = None) -> TaskGraph:
        """From rows a, b and optionally w, in either or both directions: mirrored, fused by summing, without loops."""
        edges = symmetrized(pairs)
        if vertices is None:
            vertices = edges.select(F.col("src").alias("id")).distinct().withColumn("c", F.lit(1).cast("long"))
        return cls(vertices.select(F.col("id").cast("long").alias("id"), F.col("c").cast("long").alias("c")), edges)

    def persist(self) -> TaskGraph:
        from pyspark import StorageLevel

        return TaskGraph(self.vertices.persist(StorageLevel.MEMORY_AND_DISK), self.edges.persist(StorageLevel.MEMORY_AND_DISK))

    def unpersist(self) -> None:
        self.vertices.unpersist()
        self.edges.unpersist()


def keyed(df: DataFrame) -> DataFrame:
    """The side of a join that grows with the vertices: sorted and merged, never broadcast.

    Of a stored table Spark knows the compressed size of the columns read, a few bytes a row, and would build a table of a
    million rows on the driver.
    """
    return df.hint("merge")


def symmetrized(pairs: DataFrame) -> DataFrame:
    """src, dst, w: asymmetric volumes as symmetric ones, the sum of both directions."""
    w = F.col("w").cast("long") if "w" in pairs.columns else F.lit(1).cast("long")
    one = pairs.filter("a <> b").select(F.col("a").cast("long").alias("src"), F.col("b").cast("long").alias("dst"), w.alias("w"))
    # sum the undirected pair first, so that the mirror image doubles what is left and not what comes in
    fused = one.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "w").groupBy("src", "dst").agg(F.sum("w").alias("w"))
    ends = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return fused.select(F.explode(ends).alias("e"), "w").select("e.src", "e.dst", "w")


def validation(graph: TaskGraph) -> DataFrame:
    """check, violations: what a task graph must not have, one row for each rule."""
    v, e = graph.vertices, graph.edges
    known = keyed(v.select("id"))
    loose = e.select(F.col("src").alias("id")).join(known, "id", "left_anti")
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    checks = [
        ("asymmetric", e.join(keyed(back), ["src", "dst", "w"], "left_anti")),
        ("endpoint_unknown", loose),
        ("loop", e.filter("src = dst")),
        ("nonpositive_c", v.filter("c is null or c <= 0")),
        ("nonpositive_w", e.filter("w is null or w <= 0")),
        ("pair_twice", e.groupBy("src", "dst").count().filter("count > 1")),
        ("vertex_twice", v.groupBy("id").count().filter("count > 1")),
    ]
    rows = [df.agg(F.count("*").alias("violations")).select(F.lit(name).alias("check"), "violations") for name, df in checks]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def degrees(graph: TaskGraph) -> DataFrame:
    """id, deg, wdeg for every vertex, isolated ones included."""
    own = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"), F.sum("w").alias("wdeg"))
    return graph.vertices.select("id").join(keyed(own), "id", "left").select("id", F.coalesce("deg", F.lit(0)).alias("deg"), F.coalesce("wdeg", F.lit(0)).alias("wdeg"))


def summary(graph: TaskGraph) -> DataFrame:
    """n, m (undirected), w_total (undirected), c_total, max_deg, isolated in one row."""
    own = degrees(graph).join(keyed(graph.vertices), "id")
    half = lambda c: F.floor(F.coalesce(F.sum(c), F.lit(0)) / 2).cast("long")
    return own.agg(
        F.count("*").alias("n"), half("deg").alias("m"), half("wdeg").alias("w_total"), F.sum("c").cast("long").alias("c_total"), F.max("deg").alias("max_deg"), F.count_if(F.col("deg") == 0).alias("isolated")
    )


def split_by_block(graph: TaskGraph, mapping: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All blocks' subgraphs at once: vertices(id, c, part) and edges(src, dst, w, part), cross edges gone.

    One pass over the edges for all blocks: the block's number is a column, not a loop.
    """
    part = mapping.select("id", F.col("pe").alias("part"))
    vertices = graph.vertices.join(keyed(part), "id")
    s = part.select(F.col("id").alias("src"), F.col("part").alias("part"))
    t = part.select(F.col("id").alias("dst"), F.col("part").alias("other"))
    edges = graph.edges.join(keyed(s), "src").join(keyed(t), "dst").filter("part = other").select("src", "dst", "w", "part")
    return vertices, edges


def subgraph_sizes(graph: TaskGraph, mapping: DataFrame) -> DataFrame:
    """part, n, w (vertex weight), m (undirected edges)."""
    vertices, edges = split_by_block(graph, mapping)
    sizes = vertices.groupBy("part").agg(F.count("*").alias("n"), F.sum("c").alias("w"))
    count = edges.filter("src < dst").groupBy("part").agg(F.count("*").alias("m"))
    return sizes.join(count, "part", "left").select("part", "n", "w", F.coalesce("m", F.lit(0)).alias("m"))


def dense_ids(df: DataFrame, id: str = "id", part: str | None = None, buckets: int = 64) -> DataFrame:
    """df with new_id: 0, 1, 2, ... in the order of id (within part). Ids must be unique.

    Ranks come in two steps: rows are counted by ranges of ids, the ranges' counts are summed up, and only the rows of one
    range are ordered together. Ranges hold equal spans between least and largest id.
    """
    from pyspark.sql import Window as W

    ends = df.agg(F.min(id).alias("a"), F.max(id).alias("b")).head()
    low, high = ends["a"] or 0, ends["b"] or 0
    width = max(1, (high - low) // buckets + 1)
    keys = [part] if part else []
    own = df.withColumn("__range", F.floor((F.col(id) - F.lit(low)) / F.lit(width)).cast("int"))
    sizes = own.groupBy(*keys, "__range").agg(F.count("*").alias("__n"))
    before = W.partitionBy(*(keys or [F.lit(0)])).orderBy("__range").rowsBetween(W.unboundedPreceding, -1)
    starts = sizes.withColumn("__start", F.coalesce(F.sum("__n").over(before), F.lit(0))).drop("__n")
    rank = F.row_number().over(W.partitionBy(*keys, "__range").orderBy(id))
    return own.join(starts, [*keys, "__range"]).withColumn("new_id", (F.col("__start") + rank - 1).cast("long")).drop("__range", "__start")


def project(mapping: DataFrame, projection: DataFrame) -> DataFrame:
    """Labels of coarse vertices for the vertices they stand for: id, pe."""
    coarse = mapping.select(F.col("id").alias("coarse_id"), "pe")
    return projection.join(keyed(coarse), "coarse_id").select("id", "pe")
