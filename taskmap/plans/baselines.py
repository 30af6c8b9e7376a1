"""The methods that the mappers are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap import objective as measures
from taskmap.config import Config
from taskmap.functions import kernels
from taskmap.graph import TaskGraph
from taskmap.plans.iterate import barrier
from taskmap.plans.multilevel import in_kernel, multilevel_map, partition_edge_cut
from taskmap.plans.multisection import multisection
from taskmap.topology import MatrixTopology, Topology, load_bound

#: Quality and speed settings of the serial baselines.
#: They run in one task whatever the graph's size, so no level goes to the distributed mapper.
SERIAL = {"small_edges": 1 << 62}
PRESETS = {"strong": {"restarts": 4, "passes": 3, "match_rounds": 12}, "fast": {"restarts": 1, "passes": 1, "patience": 4}}

#: The local search of the partitioner in serial multisection.
SEARCH = {"strong": "fm", "fast": "none"}


def place_blocks(quotient: DataFrame, topology: Topology | MatrixTopology) -> DataFrame:
    """block, pe: the one-to-one problem on a quotient graph of at most k squared rows, greedy and then by swaps, in one task."""
    k, dist = topology.k, topology.dense().astype(float)

    def run(table: pa.Table) -> pa.Table:
        volume = np.zeros((k, k))
        volume[table.column("pe_x").to_numpy(), table.column("pe_y").to_numpy()] = table.column("w").to_numpy()
        pe = kernels.place_blocks(volume, dist)
        return pa.table([pa.array(np.arange(k), pa.int32()), pa.array(pe, pa.int32())], ["block", "pe"])

    return quotient.withColumn("g", F.lit(0)).groupBy("g").applyInArrow(run, "block int, pe int")


def two_phase(graph: TaskGraph, topology: Topology | MatrixTopology, config: Config = Config()) -> DataFrame:
    """id, pe: partition by edge-cut, then place the blocks on PEs."""
    blocks = partition_edge_cut(graph, topology.k, config)
    placed = place_blocks(measures.quotient(graph, blocks), topology).withColumnRenamed("pe", "to")
    return barrier(blocks.join(F.broadcast(placed), blocks["pe"] == placed["block"], "left").select("id", F.coalesce("to", "pe").alias("pe")))


def serial_multisection(graph: TaskGraph, topology: Topology, preset: str, config: Config = Config()) -> DataFrame:
    """id, pe: multisection with the kernel partitioner at quality settings, which have the local search, or speed settings."""
    return multisection(graph, topology, config.but(**PRESETS[preset], **SERIAL, local_search=SEARCH[preset]))


def serial_integrated(graph: TaskGraph, topology: Topology, preset: str, config: Config = Config()) -> DataFrame:
    """id, pe: the multilevel mapper with serial label propagation after the last level, at quality or speed settings.

    Runs in one task whatever the size: the graph has to fit into its memory, else the task fails.
    """
    own = config.but(**PRESETS[preset], **SERIAL)
    first = multilevel_map(graph, topology, own)
    total = graph.vertices.agg(F.sum("c").alias("c")).head()["c"]
    bound = np.full(topology.k, load_bound(total, topology.k, config.eps_num, config.eps_den))
    dist, rounds = topology.dense(), 20 if preset == "strong" else 3
    return barrier(in_kernel(graph, lambda g, pe, _: kernels.sequential_lp(g, pe, dist, bound, own, rounds), start=first))


def sequential_lp(graph: TaskGraph, mapping: DataFrame, topology: Topology, config: Config = Config(), rounds: int = 10) -> DataFrame:
    """id, pe after classic label propagation from a mapping, in one task."""
    total = graph.vertices.agg(F.sum("c").alias("c")).head()["c"]
    bound = np.full(topology.k, load_bound(total, topology.k, config.eps_num, config.eps_den))
    dist = topology.dense()
    return in_kernel(graph, lambda g, pe, _: kernels.sequential_lp(g, pe, dist, bound, config, rounds), start=mapping)


def exact_mapping(graph: TaskGraph, topology: Topology | MatrixTopology, config: Config = Config()) -> DataFrame:
    """n, k, best_j by trying all mappings: for a handful of vertices."""
    k, dist = topology.k, topology.dense()

    def run(table: pa.Table) -> pa.Table:
        from taskmap.plans.multilevel import _arrays

        g, _ = _arrays(table)
        bound = np.full(k, load_bound(int(g.c.sum()), k, config.eps_num, config.eps_den))
        j, _ = kernels.exact(g, k, dist, bound)
        return pa.table([pa.array([g.n], pa.int64()), pa.array([k], pa.int32()), pa.array([j], pa.int64())], ["n", "k", "best_j"])

    from taskmap.plans.multilevel import together

    return together(graph).groupBy("part").applyInArrow(run, "n long, k int, best_j long")
