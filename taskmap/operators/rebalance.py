"""Weak and strong rebalancing.

State is a table of blocks(pe, part, weight, bound, average): one row for each PE, broadcast to vertices. Vertices of
overloaded blocks pick a target; a prefix of them, by classes of loss, moves until the block fits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.config import Config
from taskmap.objective import cut_gains, gains
from taskmap.operators.matching import edge_noise
from taskmap.topology import MatrixTopology, Topology

#: Rows of a bucket are summed up in so many groups, so that a bucket never is one task's.
SALTS = 16


def block_table(vertices: DataFrame, mapping: DataFrame, limits: DataFrame) -> DataFrame:
    """limits(pe, part, bound, average) with the weight of each PE."""
    loads = vertices.join(mapping, "id").groupBy("pe").agg(F.sum("c").alias("weight"))
    return limits.join(F.broadcast(loads), "pe", "left").select("pe", "part", "bound", "average", F.coalesce("weight", F.lit(0)).cast("long").alias("weight"))


def sigma(config: Config) -> Column:
    """Up to which weight a block takes vertices in weak rebalancing."""
    gap = F.lit(config.sigma_gap)
    if config.sigma_mode == "scaled":
        gap = F.least(gap, F.call_function("div", F.col("bound") - F.col("average"), F.lit(2)))
    return F.col("bound") - gap


def candidates(vertices: DataFrame, mapping: DataFrame, blocks: DataFrame, config: Config) -> DataFrame:
    """id, c, pe_old, part, weight, bound: vertices of overloaded blocks that are not too heavy to move.

    Too heavy is more than 3/2 of what the block has above the average (in integers: 2 c > 3 excess).
    """
    over = F.broadcast(blocks.filter("weight > bound"))
    own = vertices.join(mapping, "id").join(over, "pe")
    fits = F.lit(config.heavy_den) * F.col("c") <= F.lit(config.heavy_num) * (F.col("weight") - F.col("average"))
    return own.filter(fits).select("id", "c", F.col("pe").alias("pe_old"), "part", "weight", "bound")


def loss_bucket(gain: Column) -> Column:
    """0 for gains, 1 for no change, then 2 + the floor of the loss's binary logarithm; exact in integers."""
    return F.when(gain > 0, F.lit(0)).when(gain == 0, F.lit(1)).otherwise(F.length(F.bin(-gain)) + 1).cast("int")


def targets(movers: DataFrame, conn: DataFrame, mapping: DataFrame, blocks: DataFrame, topology: Topology | MatrixTopology, config: Config, limit: Column | None = None) -> DataFrame:
    """movers with pe_new and gain: the best neighbouring block that accepts, else a pseudo-random one that does.

    The gain is by edge-cut or by communication cost, as the config says. Vertices find no target where no block accepts.
    """
    accepting = blocks.filter(F.col("weight") <= (sigma(config) if limit is None else limit)).select("pe", "part")
    measure = cut_gains if config.rebalance_objective == "cut" else lambda c, m, some=None: gains(c, m, topology, some)
    own = mapping.join(movers.select("id"), "id", "left_semi")
    some = conn.join(movers.select("id"), "id", "left_semi")
    near = some.join(F.broadcast(accepting.select("pe")), "pe").join(own.withColumnRenamed("pe", "pe_old"), "id").filter("pe <> pe_old").select("id", F.col("pe").alias("pe_new"))
    best = F.max_by(F.struct("pe_new", "gain"), F.struct("gain", -F.col("pe_new"))).alias("b")
    first = measure(some, own, near).groupBy("id").agg(best).select("id", "b.pe_new", "b.gain")
    lists = accepting.groupBy("part").agg(F.array_sort(F.collect_list("pe")).alias("pes"))  # k entries in all
    rest = movers.join(first.select("id"), "id", "left_anti").join(F.broadcast(lists), "part")
    pick = F.element_at("pes", (edge_noise(F.col("id"), F.col("id"), config.seed) % F.size("pes") + 1).cast("int"))
    rest = rest.select("id", pick.alias("pe_new"))
    second = measure(some, own, rest).select("id", "pe_new", "gain")
    # an isolated vertex has no connectivity and loses nothing
    second = rest.join(second.select("id", "gain"), "id", "left").select("id", "pe_new", F.coalesce("gain", F.lit(0)).cast("long").alias("gain"))
    return movers.join(first.unionByName(second), "id")


def running(df: DataFrame, keys: list[str], order: list[str], value: str, name: str) -> DataFrame:
    """df with the sum of value over the rows of keys before each row, in that order, whose first column is a bucket.

    Two steps: sums of buckets, which are few, then sums within a bucket.
    """
    bucket = order[0]
    sums = df.groupBy(*keys, bucket).agg(F.sum(value).alias("__s"))
    earlier = W.partitionBy(*keys).orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    starts = sums.withColumn("__start", F.coalesce(F.sum("__s").over(earlier), F.lit(0))).drop("__s")
    inside = W.partitionBy(*keys, bucket).orderBy(*order[1:]).rowsBetween(W.unboundedPreceding, -1)
    own = df.withColumn("__in", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return own.join(F.broadcast(starts), [*keys, bucket]).withColumn(name, (F.col("__start") + F.col("__in")).cast("long")).drop("__start", "__in")


def prefixes(movers: DataFrame) -> DataFrame:
    """The vertices that must move: those with less weight before them than the block has above its bound."""
    own = movers.withColumn("bucket", loss_bucket(F.col("gain")))
    own = running(own, ["pe_old"], ["bucket", "id"], "c", "before")
    return own.filter(F.col("before") < F.col("weight") - F.col("bound"))


REBALANCE = ["id", "pe_old", "pe_new", "gain", "bucket", "before"]


def weak(vertices: DataFrame, conn: DataFrame, mapping: DataFrame, blocks: DataFrame, topology: Topology | MatrixTopology, config: Config) -> DataFrame:
    """id, pe_old, pe_new, gain, bucket, before of the moves; targets may become overloaded."""
    movers = candidates(vertices, mapping, blocks, config)
    return prefixes(targets(movers, conn, mapping, blocks, topology, config)).select(*REBALANCE)


def strong(vertices: DataFrame, conn: DataFrame, mapping: DataFrame, blocks: DataFrame, topology: Topology | MatrixTopology, config: Config) -> DataFrame:
    """The same without overfilling a target.

    All movers of a part get intervals of a line by (bucket, id), its blocks with room get intervals as long as their room
    by PE; a mover goes where its interval lies wholly inside one of them. Who lies across a border waits. The join is by
    interval against one row for each PE.
    """
    movers = candidates(vertices, mapping, blocks, config)
    chosen = prefixes(targets(movers, conn, mapping, blocks, topology, config, limit=F.col("bound") - 1))
    line = running(chosen.drop("before"), ["part"], ["bucket", "id"], "c", "start").withColumnRenamed("bucket", "bucket_")
    room = blocks.filter("weight < bound").select("part", F.col("pe").alias("pe_to"), (F.col("bound") - F.col("weight")).alias("room"))
    upto = F.sum("room").over(W.partitionBy("part").orderBy("pe_to"))
    places = room.select("part", "pe_to", (upto - F.col("room")).alias("low"), upto.alias("high"))
    fits = (F.col("start") >= F.col("low")) & (F.col("start") + F.col("c") <= F.col("high"))
    own = line.join(F.broadcast(places), "part").filter(fits)
    return own.select("id", "pe_old", F.col("pe_to").alias("pe_new"), "gain", F.col("bucket_").alias("bucket"), F.col("start").alias("before"))
