"""The engine from SQL: scalar functions that Catalyst inlines, a table function, an aggregate, and views."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf

from taskmap.graph import TaskGraph
from taskmap.operators.noise import NOISE_FACTORS, NOISE_MODULUS
from taskmap.topology import Topology


def scalar_functions(topology: Topology) -> dict[str, str]:
    p, (x, y, z) = NOISE_MODULUS, NOISE_FACTORS
    return {
        "pe_distance": f"(x INT, y INT) RETURNS BIGINT RETURN {topology.distance_sql('x', 'y')}",
        "load_bound": "(total BIGINT, k BIGINT, num BIGINT, den BIGINT) RETURNS BIGINT RETURN ((den + num) * total + den * k - 1) div (den * k)",
        "adaptive_eps": "(total DOUBLE, part DOUBLE, k DOUBLE, k_part DOUBLE, eps DOUBLE, levels DOUBLE) RETURNS DOUBLE RETURN greatest(0.0D, pow((1 + eps) * k_part * total / (k * part), 1 / levels) - 1)",
        "edge_noise": f"(a BIGINT, b BIGINT, seed BIGINT) RETURNS BIGINT RETURN ((least(a, b) % {p}) * {x}L + (greatest(a, b) % {p}) * {y}L + (seed % {p}) * {z}L) % {p}",
        "loss_bucket": "(gain BIGINT) RETURNS INT RETURN CASE WHEN gain > 0 THEN 0 WHEN gain = 0 THEN 1 ELSE length(bin(-gain)) + 1 END",
    }


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("pe", "l1", "l2", "l3")]))
class TopologyPes:
    """The PEs of a tree of up to three levels, with their components."""

    def eval(self, hierarchy: str, distance: str):
        t = Topology.parse(hierarchy, distance)
        for pe in range(t.k):
            at = [pe // n for n in t.sizes] + [None] * 3
            yield (pe, *at[:3])


@pandas_udf(T.DoubleType())
def geo_mean_udf(x: pd.Series) -> float:
    """The geometric mean of positive numbers, as a grouped aggregate over Arrow."""
    import numpy as np

    return float(np.exp(np.log(x).mean()))


def register_sql(spark: SparkSession, topology: Topology, graph: TaskGraph | None = None, mapping=None) -> None:
    """Functions pe_distance, load_bound, adaptive_eps, edge_noise, loss_bucket, topology_pes and geo_mean, and views tasks,
    edges, mapping and pes."""
    for name, text in scalar_functions(topology).items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{text}")
    spark.udtf.register("topology_pes", TopologyPes)
    spark.udf.register("geo_mean", geo_mean_udf)
    topology.pes(spark).createOrReplaceTempView("pes")
    if graph is not None:
        graph.vertices.createOrReplaceTempView("tasks")
        graph.edges.createOrReplaceTempView("edges")
    if mapping is not None:
        mapping.createOrReplaceTempView("mapping")
