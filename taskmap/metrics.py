"""Comparing algorithms over instances and seeds: runs(algorithm, instance, hierarchy, seed, n, j, seconds)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.plans.iterate import Clock

RUNS = "algorithm string, instance string, hierarchy string, seed int, n long, j long, edge_cut long, max_block long, seconds double"
ROUND_LOG = "level int, phase string, round int, n long, m long, j long, max_block long, moved long, seconds double"

KEY = ["algorithm", "instance", "hierarchy"]
#: Instances below so many vertices count as small.
SMALL = 1_000_000


def seed_average(runs: DataFrame) -> DataFrame:
    """algorithm, instance, hierarchy, n, j, seconds: means over seeds."""
    return runs.groupBy(*KEY).agg(F.max("n").alias("n"), F.avg("j").alias("j"), F.avg("seconds").alias("seconds"))


def with_best(means: DataFrame) -> DataFrame:
    return means.withColumn("best", F.min("j").over(W.partitionBy("instance", "hierarchy")))


def performance_profile(means: DataFrame, taus: list[float]) -> DataFrame:
    """algorithm, tau, share: the share of instances that the algorithm solves within tau times the best.

    The grid of tau values is a literal array, exploded, so no join is needed.
    """
    own = with_best(means).withColumn("tau", F.explode(F.array(*[F.lit(float(t)) for t in taus])))
    return own.groupBy("algorithm", "tau").agg(F.round(F.avg((F.col("j") <= F.col("tau") * F.col("best")).cast("double")), 6).alias("share"))


def best_share(means: DataFrame) -> DataFrame:
    """algorithm, n_best, n_instances, share of instances with the best solution."""
    hit = (F.col("j") == F.col("best")).cast("int")
    return with_best(means).groupBy("algorithm").agg(F.sum(hit).alias("n_best"), F.count("*").alias("n_instances"), F.round(F.avg(hit), 6).alias("share"))


def excess_over_best(means: DataFrame) -> DataFrame:
    """algorithm, mean_excess, worst_ratio. Instances whose best cost is 0 count where the algorithm meets it."""
    ratio = F.when(F.col("j") == F.col("best"), F.lit(1.0)).otherwise(F.try_divide(F.col("j"), F.col("best")))
    return with_best(means).groupBy("algorithm").agg(F.round(F.avg(ratio) - 1, 6).alias("mean_excess"), F.round(F.max(ratio), 6).alias("worst_ratio"))


def geo_mean(x) -> F.Column:
    return F.round(F.exp(F.avg(F.log(x))), 6)


def speedups(means: DataFrame, base: str) -> DataFrame:
    """algorithm, geo_mean, min, max of the base's time over the algorithm's."""
    b = means.filter(F.col("algorithm") == base).select("instance", "hierarchy", F.col("seconds").alias("base_s"))
    own = means.join(b, ["instance", "hierarchy"]).withColumn("x", F.try_divide("base_s", "seconds"))
    return own.groupBy("algorithm").agg(geo_mean(F.col("x")).alias("geo_mean"), F.round(F.min("x"), 6).alias("least"), F.round(F.max("x"), 6).alias("most"))


def pairwise_wins(means: DataFrame, a: str, b: str, small: int = SMALL) -> DataFrame:
    """size_class (null: all), n, better_j, faster: how often a beats b."""
    side = lambda name, tag: means.filter(F.col("algorithm") == name).select("instance", "hierarchy", F.col("n").alias(f"n_{tag}"), F.col("j").alias(f"j_{tag}"), F.col("seconds").alias(f"s_{tag}"))
    both = side(a, "a").join(side(b, "b"), ["instance", "hierarchy"])
    both = both.withColumn("size_class", F.when(F.col("n_a") < small, "small").otherwise("large"))
    return both.rollup("size_class").agg(F.count("*").alias("n"), F.count_if(F.col("j_a") < F.col("j_b")).alias("better_j"), F.count_if(F.col("s_a") < F.col("s_b")).alias("faster"))


def phase_shares(log: DataFrame) -> DataFrame:
    """phase, seconds, share of the whole."""
    sums = log.groupBy("phase").agg(F.sum("seconds").alias("seconds"))
    share = F.col("seconds") / F.sum("seconds").over(W.partitionBy())
    return sums.select("phase", F.round("seconds", 6).alias("seconds"), F.round(share, 6).alias("share"))


def phase_table(log: DataFrame, phases: list[str]) -> DataFrame:
    """A column for each phase, a row for each instance."""
    return log.groupBy("instance").pivot("phase", phases).agg(F.round(F.sum("seconds"), 6))


def round_log(spark, clock: Clock) -> DataFrame:
    """The clock's rows as a table."""
    rows = [(r.get("level", 0), r["phase"], r.get("round"), r.get("n"), r.get("m"), None, None, r.get("moved"), float(r["seconds"])) for r in clock.rows]
    return spark.createDataFrame(rows, ROUND_LOG)
