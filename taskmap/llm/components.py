"""Connected components of links, as repeated star contractions: two aggregations and joins a round, O(log n) rounds.

Every task handles rows of links; a node with very many links is met by partial aggregation and by the engine's splitting
of skewed joins, and nothing is gathered on the driver but one count a round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.llm.common import stored


def _settled(pairs: DataFrame) -> bool:
    """Whether pairs(u, v) are stars: no node has two centres, and no centre has one itself."""
    one = lambda name, low, high: pairs.select(F.col(name).alias("x"), F.lit(low).alias("low"), F.lit(high).alias("high"))
    seen = one("u", 1, 0).unionByName(one("v", 0, 1)).groupBy("x").agg(F.sum("low").alias("low"), F.max("high").alias("high"))
    return not seen.filter("low > 1 OR (low > 0 AND high > 0)").limit(1).count()


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, component: the smallest node that links(a, b) reach; only nodes that have a link to another one."""
    pairs = stored(links.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    for _ in range(most_rounds):
        if _settled(pairs):
            break
        # large star: what is larger than a node is linked with the node's least neighbour
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # small star: a node and its smaller neighbours are linked with the least of these
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        pairs = stored(small.filter("u <> v").distinct())
    else:
        raise RuntimeError("components did not settle")
    stars = pairs.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.unionByName(pairs.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
