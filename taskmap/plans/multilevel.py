"""Multilevel plans: coarsening, initial mapping, and refinement back to the full graph.

One driver loop serves one graph or many parts at once: with parts, edges between them are gone, blocks are numbered
through all parts, and each part has its own bound, so all parts are coarsened and refined in the same stages.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.config import Config
from taskmap.functions import kernels
from taskmap.graph import TaskGraph
from taskmap.operators.contraction import completed, contract, uncontract
from taskmap.operators.matching import cluster, heavy_edge_matching
from taskmap.plans.iterate import Clock, barrier
from taskmap.plans.refine import limits, refine
from taskmap.topology import MatrixTopology, Topology, load_bound


@dataclass
class Level:
    graph: TaskGraph
    n: int
    m: int
    projection: DataFrame | None  # to the next coarser level


def _sized(graph: TaskGraph) -> tuple[int, int]:
    return graph.vertices.count(), graph.edges.count()


def _projection(graph: TaskGraph, bound: int | None, config: Config, part: DataFrame | None, method: str) -> DataFrame:
    """id, coarse_id of all vertices by one of the methods."""
    if method == "matching":
        matched, _, _ = heavy_edge_matching(graph, bound, config, part)
        return barrier(completed(graph.vertices, matched))
    most = max(2, (bound or 1 << 62) // config.cluster_share)
    return barrier(cluster(graph, most, config.cluster_rounds, config.seed))


def coarsen(graph: TaskGraph, bound: int | None, least: int, config: Config, clock: Clock | None = None, part: DataFrame | None = None) -> list[Level]:
    """Levels from fine to coarse: until fewer than `least` vertices, or the graph is small enough for one task's kernel
    (config.small_edges). A level that matchings shrink too little is clustered; one that clusters shrink too little is the last."""
    clock = clock or Clock()
    n, m = _sized(graph)
    levels = [Level(graph, n, m, None)]
    while n >= least and m > config.small_edges and len(levels) <= config.levels:
        for method in dict.fromkeys((config.coarsening, "cluster")):
            with clock.phase("coarsen", len(levels) - 1, n=n, m=m):
                projection = _projection(graph, bound, config, part, method)
            with clock.phase("contract", len(levels) - 1):
                small = contract(graph, projection)
                small = TaskGraph(barrier(small.vertices), barrier(small.edges))
                size = _sized(small)
            if shrunk := size[0] <= (1 - config.least_shrink) * n:
                break
        if not shrunk:
            break
        if part is not None:
            part = barrier(part.join(projection, "id").select(F.col("coarse_id").alias("id"), "part").distinct())
        graph, (n, m) = small, size
        levels[-1].projection = projection
        levels.append(Level(graph, n, m, None))
    return levels


def scattered(graph: TaskGraph, k: int | DataFrame, part: DataFrame | None = None) -> DataFrame:
    """id, pe: vertices dealt to blocks by their noise, all blocks of about equal numbers; refinement starts from anything.

    With part, k blocks of each part, numbered part * k on.
    """
    deal = F.pmod(F.xxhash64("id"), F.lit(k))
    if part is None:
        return graph.vertices.select("id", deal.cast("int").alias("pe"))
    return part.select("id", (F.col("part") * k + deal).cast("int").alias("pe"))


def _arrays(table: pa.Table) -> tuple[kernels.Small, np.ndarray]:
    """A small graph from rows that are vertices (src null) or edges."""
    src = table.column("src")
    v, e = table.filter(src.is_null()), table.filter(src.is_valid())
    col = lambda t, c: t.column(c).to_numpy()
    return kernels.Small.of(col(v, "id"), col(v, "c"), col(e, "src"), col(e, "dst"), col(e, "w"))


def together(graph: TaskGraph, part: DataFrame | None = None, start: DataFrame | None = None) -> DataFrame:
    """Vertices and edges as rows of one table, by part: what a kernel's task reads."""
    v = graph.vertices.join(part, "id") if part is not None else graph.vertices.withColumn("part", F.lit(0))
    v = v.join(start, "id", "left") if start is not None else v.withColumn("pe", F.lit(None).cast("int"))
    none = F.lit(None).cast("long")
    rows = v.select("part", "id", "c", none.alias("src"), none.alias("dst"), none.alias("w"), "pe")
    e = graph.edges
    if part is not None:
        e = e.join(part.select(F.col("id").alias("src"), "part"), "src")
    else:
        e = e.withColumn("part", F.lit(0))
    return rows.unionByName(e.select("part", none.alias("id"), none.alias("c"), "src", "dst", "w", F.lit(None).cast("int").alias("pe")))


def in_kernel(graph: TaskGraph, run, part: DataFrame | None = None, start: DataFrame | None = None) -> DataFrame:
    """id, pe from run(Small, start or None, part), one task for each part. For graphs below config.small_edges, and the serial baselines."""

    given = start is not None

    def task(key: tuple, table: pa.Table) -> pa.Table:
        small, ids = _arrays(table)
        if given:
            v = table.filter(table.column("src").is_null())
            pe = v.column("pe").to_numpy()[np.argsort(v.column("id").to_numpy())].astype(np.int64)
        else:
            pe = None
        return pa.table([pa.array(ids, pa.int64()), pa.array(np.asarray(run(small, pe, key[0].as_py()), np.int32))], ["id", "pe"])

    return together(graph, part, start).groupBy("part").applyInArrow(task, "id long, pe int")


def initial_mapping(coarse: TaskGraph, topology: Topology, total: int, config: Config) -> DataFrame:
    """id, pe of the coarsest graph by multisection along the tree, in one task; restarts keep the best. The task's graph has
    fewer than coarsest_factor * k vertices, whatever the input's size."""
    dist = topology.dense()
    bound = np.full(topology.k, load_bound(total, topology.k, config.eps_num, config.eps_den))

    def run(g: kernels.Small, _, __):
        found = []
        for r in range(max(1, config.restarts)):
            pe = kernels.multisection(g, topology, config.but(seed=config.seed + r, passes=1), total)
            load = np.bincount(pe, weights=g.c, minlength=len(bound))
            found.append((max(0, int((load - bound).max())), kernels.objective(g, pe, dist), r, pe))
        return min(found, key=lambda x: x[:3])[3]

    return in_kernel(coarse, run)


def back(levels: list[Level], mapping: DataFrame, topology: Topology | MatrixTopology, blocks: DataFrame, config: Config, clock: Clock) -> DataFrame:
    """Refines the coarsest level's mapping and takes the contractions back, refining after each."""
    mapping = refine(levels[-1].graph, mapping, topology, blocks, config, clock, len(levels) - 1)
    for i in range(len(levels) - 2, -1, -1):
        with clock.phase("uncontract", i):
            mapping = barrier(uncontract(mapping, levels[i].projection))
        mapping = refine(levels[i].graph, mapping, topology, blocks, config, clock, i)
    return mapping


def multilevel_map(graph: TaskGraph, topology: Topology | MatrixTopology, config: Config = Config(), clock: Clock | None = None) -> DataFrame:
    """id, pe: the direct multilevel mapper. The communication cost is the objective at every level.

    Levels above the kernel's size are coarsened and refined on the cluster; the first level below is finished in one task
    (coarsening, initial mapping and refinement to that level).
    """
    clock = clock or Clock()
    spark = graph.vertices.sparkSession
    total = graph.vertices.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("c")).head()["c"]
    k = topology.k
    bound = load_bound(total, k, config.eps_num, config.eps_den)
    levels = coarsen(graph, bound, config.coarsest_factor * k, config, clock)
    tree = topology if isinstance(topology, Topology) else Topology.flat(k)
    dist = topology.dense()
    if levels[-1].m <= config.small_edges:
        bounds = np.full(k, bound)

        def finish(g: kernels.Small, _, __):
            begin = lambda small, c: kernels.multisection(small, tree, c.but(passes=1), total)
            return kernels.multilevel(g, dist, bounds, config, begin)

        with clock.phase("initial", len(levels) - 1):
            mapping = barrier(in_kernel(levels[-1].graph, finish))
        if len(levels) == 1:
            return mapping
        with clock.phase("uncontract", len(levels) - 2):
            mapping = barrier(uncontract(mapping, levels[-2].projection))
        return back(levels[:-1], mapping, topology, limits(spark, k, total, config), config, clock)
    with clock.phase("initial", len(levels) - 1):
        # coarsening that ended early leaves more than a task should hold
        few = levels[-1].n < config.coarsest_factor * k
        mapping = barrier(initial_mapping(levels[-1].graph, tree, total, config) if few else scattered(levels[-1].graph, k))
    return back(levels, mapping, topology, limits(spark, k, total, config), config, clock)


def partition_edge_cut(graph: TaskGraph, k: int, config: Config = Config(), clock: Clock | None = None) -> DataFrame:
    """id, pe: the multilevel edge-cut partitioner; as a mapper it takes block numbers for PEs and ignores the machine."""
    own = config.but(filter_mode="relaxed")
    return multilevel_map(graph, Topology.flat(k), own, clock)


def split_parts(graph: TaskGraph, part: DataFrame, arity: int, bounds: DataFrame, config: Config, clock: Clock) -> DataFrame:
    """id, pe: every part into `arity` blocks by edge-cut, block s of part p numbered p * arity + s.

    bounds(part, bound, average) has a row for each part, at most k in all. Small parts are one task each; otherwise all
    parts are coarsened together, started part by part, and refined together.
    """
    clock = clock or Clock()
    if arity == 1:  # a part's one block is the part
        return barrier(part.select("id", F.col("part").cast("int").alias("pe")))
    rows = {r["part"]: r["bound"] for r in bounds.collect()}  # at most k rows
    numbered = lambda pe, p: np.asarray(pe) + p * arity
    inner = config.but(filter_mode="relaxed")

    def whole(g: kernels.Small, _, p):
        return numbered(kernels.partition(g, np.full(arity, rows[p]), inner), p)

    sizes = graph.edges.join(part.select(F.col("id").alias("src"), "part"), "src").groupBy("part").count().agg(F.max("count").alias("m")).head()["m"] or 0
    if sizes <= config.small_edges:
        with clock.phase("initial"):
            return barrier(in_kernel(graph, whole, part))
    heaviest = max(rows.values())
    levels = coarsen(graph, heaviest, config.coarsest_factor * arity * len(rows), config, clock, part=part)
    coarse_part = part
    for level in levels[:-1]:
        coarse_part = barrier(coarse_part.join(level.projection, "id").select(F.col("coarse_id").alias("id"), "part").distinct())
    with clock.phase("initial", len(levels) - 1):
        few = levels[-1].m <= config.small_edges or levels[-1].n < config.coarsest_factor * arity * len(rows)
        mapping = barrier(in_kernel(levels[-1].graph, whole, coarse_part) if few else scattered(levels[-1].graph, arity, coarse_part))
    spread = bounds.select("part", "bound", "average", F.explode(F.sequence(F.lit(0), F.lit(arity - 1))).alias("s"))
    blocks = barrier(spread.select((F.col("part") * arity + F.col("s")).cast("int").alias("pe"), "part", "bound", "average"))
    return back(levels, mapping, Topology.flat(arity * (max(rows) + 1)), blocks, inner, clock)
