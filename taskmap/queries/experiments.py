"""The experiments as queries: which method wins, and how cost and time move with each parameter.

Their results hold measured times, so there is no SQL for them; tests check the directions. EXPERIMENTS.md has the rows of a
run over all graphs, six machines and five seeds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.plans import experiments as ex

#: What a registered query runs on: a mesh, short chains and a geometric graph, small to large machines, and seeds.
GRAPHS, MACHINES, SEEDS = ["mesh", "chain", "geometric"], ["4:8:1", "4:8:3", "4:8:6"], 3


def exp_own(spark: SparkSession, d: str) -> DataFrame:
    """Both multisections and the integrated mapper against each other."""
    return ex.comparison(spark, d, GRAPHS, ex.OWN, "multisection_deep", MACHINES, SEEDS)


def exp_cpu(spark: SparkSession, d: str) -> DataFrame:
    """The mappers against the serial baselines."""
    return ex.comparison(spark, d, GRAPHS, ex.SERIAL, "serial_multisection_strong", MACHINES, SEEDS)


def exp_cut_only(spark: SparkSession, d: str) -> DataFrame:
    """The edge-cut partitioner used as a mapper, which ignores the machine."""
    return ex.comparison(spark, d, GRAPHS, ex.CUT_ONLY, "cut_only", MACHINES, SEEDS)


def exp_ablations(spark: SparkSession, d: str) -> DataFrame:
    """Filter, rebalancing objective, rating, imbalance and coarsening: the cost with the change over that without."""
    return ex.ablations(spark, d, GRAPHS, MACHINES, SEEDS)


def exp_phases(spark: SparkSession, d: str) -> DataFrame:
    """Where the integrated mapper's time goes, on the largest machine."""
    return ex.phases(spark, d, GRAPHS, MACHINES[-1], SEEDS)


def exp_layout(spark: SparkSession, d: str) -> DataFrame:
    """layout, seconds: the connectivity from edge rows and from neighbour lists."""
    return spark.createDataFrame(sorted(ex.layout(spark, d).items()), "layout string, seconds double").withColumn("seconds", F.round("seconds", 6))


QUERIES = {f.__name__: f for f in (exp_own, exp_cpu, exp_cut_only, exp_ablations, exp_phases, exp_layout)}
SQL: dict[str, str] = {}
