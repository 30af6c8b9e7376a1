"""Recursive multisection, level by level of the machine and for all parts of a level at once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from taskmap.config import Config
from taskmap.functions import kernels
from taskmap.graph import TaskGraph, split_by_block
from taskmap.plans.iterate import Clock, barrier
from taskmap.plans.multilevel import in_kernel, split_parts
from taskmap.topology import Topology, load_bound


def adaptive_eps(total: Column, part_total: Column, k: Column, k_part: Column, eps: float, levels_left: Column) -> Column:
    """The imbalance that a part's split may have: what the part may still weigh over what it does, an equal root of it for
    each level left, less one."""
    slack = F.lit(1 + eps) * k_part * total / (k * part_total)
    return F.greatest(F.lit(0.0), F.pow(slack, F.lit(1.0) / levels_left) - 1)


def part_bounds(vertices: DataFrame, part: DataFrame, total: int, k: int, below: int, arity: int, level: int, config: Config) -> DataFrame:
    """part, part_weight, levels_left, eps, bound, average of the blocks that each part is split into (one row a part)."""
    eps = config.eps_num / config.eps_den
    sums = vertices.join(part, "id").groupBy("part").agg(F.sum("c").alias("part_weight"))
    own = adaptive_eps(F.lit(total), F.col("part_weight"), F.lit(k), F.lit(below * arity), eps, F.lit(float(level))) if config.adaptive else F.lit(eps)
    least = F.call_function("div", F.col("part_weight") + F.lit(arity - 1), F.lit(arity))
    inner = F.floor((1 + F.col("eps")) * F.col("part_weight") / arity + F.lit(1e-9)).cast("long")
    leaf = F.lit(load_bound(total, k, config.eps_num, config.eps_den)) if level == 1 and config.adaptive else inner
    out = sums.withColumn("levels_left", F.lit(level)).withColumn("eps", own)
    return out.withColumn("bound", F.greatest(least, leaf)).withColumn("average", F.call_function("div", F.col("part_weight"), F.lit(arity)))


def multisection(graph: TaskGraph, topology: Topology, config: Config = Config(), clock: Clock | None = None, partitioner=None) -> DataFrame:
    """id, pe. Part p of a level is split into blocks p * arity + s, and the last level's numbers are the PEs.

    A partitioner(graph, part, arity, bounds, config, clock) -> (id, pe) can replace the edge-cut one. A graph below the
    kernel's size is mapped in one task; the sizes of the parts decide again at each level.
    """
    clock = clock or Clock()
    total = graph.vertices.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("c")).head()["c"]
    if partitioner is None and graph.edges.count() <= config.small_edges:
        with clock.phase("initial"):
            return barrier(in_kernel(graph, lambda g, _, __: kernels.multisection(g, topology, config, total)))
    split = partitioner or split_parts
    part = barrier(graph.vertices.select("id", F.lit(0).alias("part")))
    below = topology.k
    for level in range(len(topology.arity), 0, -1):
        arity = topology.arity[level - 1]
        below //= arity
        bounds = barrier(part_bounds(graph.vertices, part, total, topology.k, below, arity, level, config))
        mapping = split(graph, part, arity, bounds, config, clock)
        part = barrier(mapping.select("id", F.col("pe").alias("part")))
        if level > 1:
            with clock.phase("subgraphs", level):
                # edges between parts are gone for good, so each level moves less
                graph = TaskGraph(graph.vertices, barrier(split_by_block(graph, mapping)[1].drop("part")))
    return part.select("id", F.col("part").cast("int").alias("pe"))


def deep(config: Config) -> Config:
    from taskmap.config import DEEP_PASSES

    return config.but(passes=DEEP_PASSES)
