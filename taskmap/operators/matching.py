"""Matchings for coarsening: heavy edges by mutual preference, then two-hop rules for what is left.

No rule collects neighbour lists of unbounded length: preferences are aggregated by a maximum over (rating, noise, id), and
two-hop partners meet at one matchmaker that each of them picks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.config import Config
from taskmap.graph import TaskGraph, degrees, keyed
from taskmap.operators.noise import NOISE_FACTORS, NOISE_MODULUS
from taskmap.plans.iterate import barrier
from taskmap.plans.shards import hubs, mutual_rounds


def edge_noise(a: Column, b: Column, seed: int = 0) -> Column:
    """A number below the modulus for an undirected edge, the same from both ends; no overflow in 64 bits."""
    p, (x, y, z) = NOISE_MODULUS, NOISE_FACTORS
    low, high = F.least(a, b), F.greatest(a, b)
    return ((low % p) * F.lit(x).cast("long") + (high % p) * F.lit(y).cast("long") + F.lit((seed % p) * z).cast("long")) % p


def rated(edges: DataFrame, vertices: DataFrame, rule: str = "squared_over_product", seed: int = 0) -> DataFrame:
    """src, dst, w, cu, cv, rating, noise. Ties of ratings fall to the noise, so noise never changes a strict order."""
    u = vertices.select(F.col("id").alias("src"), F.col("c").alias("cu"))
    v = vertices.select(F.col("id").alias("dst"), F.col("c").alias("cv"))
    w = F.col("w").cast("double")
    rating = w * w / (F.col("cu") * F.col("cv")).cast("double") if rule == "squared_over_product" else w
    return edges.join(keyed(u), "src").join(keyed(v), "dst").select("src", "dst", "w", "cu", "cv", rating.alias("rating"), edge_noise(F.col("src"), F.col("dst"), seed).alias("noise"))


def preferences(rating: DataFrame, bound: int | Column | None = None, matched: DataFrame | None = None) -> DataFrame:
    """id, pref: the unmatched neighbour of highest rating that is not too heavy together with the vertex."""
    own = rating
    if matched is not None:
        taken = keyed(matched.select("id"))
        own = own.join(taken.withColumnRenamed("id", "src"), "src", "left_anti").join(taken.withColumnRenamed("id", "dst"), "dst", "left_anti")
    if bound is not None:
        own = own.filter(F.col("cu") + F.col("cv") <= (bound if isinstance(bound, Column) else F.lit(bound)))
    return own.groupBy(F.col("src").alias("id")).agg(F.max_by("dst", F.struct("rating", "noise", "dst")).alias("pref"))


def mutual_pairs(prefs: DataFrame) -> DataFrame:
    """id, coarse_id for both ends of every mutual preference; the smaller id stands for the pair."""
    back = prefs.select(F.col("id").alias("pref"), F.col("pref").alias("back"))
    return prefs.join(keyed(back), "pref").filter("back = id").select("id", F.least("id", "pref").alias("coarse_id"))


def paired(members: DataFrame, key: str, order: str = "id") -> DataFrame:
    """id, coarse_id: members of a key two by two in order; an odd last one is left."""
    w = W.partitionBy(key).orderBy(order)
    rank = F.row_number().over(w) - 1
    ranked = members.select("id", key, rank.alias("r")).withColumn("slot", F.call_function("div", F.col("r"), F.lit(2)))
    mates = ranked.groupBy(key, "slot").agg(F.min("id").alias("coarse_id"), F.count("*").alias("n")).filter("n = 2")
    return ranked.join(keyed(mates), [key, "slot"]).select("id", "coarse_id")


def unmatched(vertices: DataFrame, matched: DataFrame) -> DataFrame:
    return vertices.join(keyed(matched.select("id")), "id", "left_anti")


def match_leaves(graph: TaskGraph, matched: DataFrame) -> DataFrame:
    """Unmatched vertices of degree one at the same neighbour, two by two."""
    leaves = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"), F.max("dst").alias("hub")).filter("deg = 1")
    return paired(unmatched(leaves, matched).select("id", "hub"), "hub")


def neighbourhoods(graph: TaskGraph, only: DataFrame) -> DataFrame:
    """id, deg, print: an order-free fingerprint of the set of neighbours of the vertices in only.

    The degree and four sums of differently scrambled ids, 128 bits each: no list is collected, whatever the degree.
    """
    own = graph.edges.join(only.select(F.col("id").alias("src")), "src", "left_semi")
    h = lambda salt: F.sum(F.xxhash64("dst", F.lit(salt)).cast("decimal(38,0)")).alias(f"h{salt}")
    prints = own.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"), *[h(x) for x in (1, 2, 3, 4)])
    return prints.select("id", "deg", F.struct("deg", "h1", "h2", "h3", "h4").alias("print"))


def verified_twins(graph: TaskGraph, pairs: DataFrame) -> DataFrame:
    """Of pairs (id, coarse_id), two rows each, those whose neighbours are the same, edge by edge."""
    near = graph.edges.join(pairs.withColumnRenamed("id", "src"), "src").groupBy("coarse_id", "dst").agg(F.count("*").alias("n"))
    odd = near.filter("n <> 2").select("coarse_id").distinct()
    return pairs.join(odd, "coarse_id", "left_anti").select("id", "coarse_id")


def match_twins(graph: TaskGraph, matched: DataFrame) -> DataFrame:
    """Unmatched vertices with the same neighbours, two by two."""
    left = unmatched(graph.vertices, matched)
    return verified_twins(graph, paired(neighbourhoods(graph, left).select("id", "print"), "print"))


def match_relatives(graph: TaskGraph, matched: DataFrame, seed: int = 0, rule: str = "squared_over_product") -> DataFrame:
    """Unmatched vertices two hops apart: each picks its best-rated neighbour as matchmaker, who pairs its suitors.

    So no two-hop join is formed, and each vertex is one row.
    """
    left = unmatched(graph.vertices, matched).select("id")
    own = graph.edges.join(left.withColumnRenamed("id", "src"), "src", "left_semi")
    makers = rated(own, graph.vertices, rule, seed).groupBy(F.col("src").alias("id")).agg(F.max_by("dst", F.struct("rating", "noise", "dst")).alias("maker"))
    return paired(makers, "maker")


def match_isolated(graph: TaskGraph, matched: DataFrame, buckets: int = 64) -> DataFrame:
    """Vertices without edges, two by two by weight, within buckets of ids."""
    alone = degrees(graph).filter("deg = 0").select("id")
    own = unmatched(graph.vertices.join(alone, "id", "left_semi"), matched).withColumn("bucket", F.pmod(F.xxhash64("id"), F.lit(buckets)))
    return paired(own.withColumn("order", F.struct("c", "id")), "bucket", "order")


def light_pairs(pairs: DataFrame, vertices: DataFrame, bound: int | None) -> DataFrame:
    """Pairs whose weight together is within the bound."""
    if bound is None:
        return pairs
    own = pairs.join(vertices, "id").groupBy("coarse_id").agg(F.sum("c").alias("both")).filter(F.col("both") <= bound).select("coarse_id")
    return pairs.join(own, "coarse_id", "left_semi").select("id", "coarse_id")


def _mutual_rounds(graph: TaskGraph, bound: int | None, config: Config, n: int) -> tuple[DataFrame, int]:
    """The rounds of mutual preference over rows, for graphs with a vertex whose edges no task should hold."""
    rating = barrier(rated(graph.edges, graph.vertices, config.rating, config.seed))
    matched = barrier(graph.vertices.limit(0).select("id", F.col("id").alias("coarse_id")))
    done = 0
    for _ in range(config.match_rounds):
        new = barrier(mutual_pairs(preferences(rating, bound, matched)))
        count = new.count()
        if not count:
            break
        matched, done = barrier(matched.unionByName(new)), done + count
        rating = barrier(rating.join(new.select(F.col("id").alias("src")), "src", "left_anti").join(new.select(F.col("id").alias("dst")), "dst", "left_anti"))
        if done > config.match_target * n:
            break
    return matched, done


def heavy_edge_matching(graph: TaskGraph, bound: int | None, config: Config, part: DataFrame | None = None) -> tuple[DataFrame, int, int]:
    """The matching of a level: id, coarse_id of matched vertices; vertices and how many of them are matched.

    Rounds of mutual preference until no pair is new, the cap is met or enough is matched; then leaves, twins, relatives
    and isolated vertices, until enough is matched. With part (id, part) only vertices of one part are isolated's partners.
    """
    n = graph.vertices.count()
    if hubs(graph):
        matched, done = _mutual_rounds(graph, bound, config, n)
    else:
        matched, done = mutual_rounds(graph, bound, config.rating, config.seed, config.match_rounds, config.match_target)
    for rule in (match_leaves, match_twins, lambda g, m: match_relatives(g, m, config.seed, config.rating), match_isolated):
        if done > config.match_target * n:
            break
        pairs = rule(graph, matched)
        if part is not None and rule is match_isolated:
            inside = pairs.join(part, "id").groupBy("coarse_id").agg(F.count_distinct("part").alias("p")).filter("p = 1").select("coarse_id")
            pairs = pairs.join(inside, "coarse_id", "left_semi").select("id", "coarse_id")
        new = barrier(light_pairs(pairs, graph.vertices, bound))
        count = new.count()
        if count:
            matched, done = barrier(matched.unionByName(new)), done + count
    return matched, n, done


def cluster(graph: TaskGraph, most: int, rounds: int = 6, seed: int = 0) -> DataFrame:
    """id, coarse_id: clusters of at most that weight by label propagation on volume, the alternative to matchings.

    In a round, half of the vertices (by the noise of id and round) choose the neighbouring cluster of largest volume that
    has room; a cluster admits its suitors in order of volume while there is room.
    """
    labels = barrier(graph.vertices.select("id", F.col("id").alias("coarse_id")))
    for r in range(rounds):
        weights = graph.vertices.join(labels, "id").groupBy("coarse_id").agg(F.sum("c").alias("full"))
        turn = edge_noise(F.col("id"), F.col("id"), seed + r) % 2 == 0
        movers = graph.vertices.join(labels, "id").filter(turn).select("id", "c", F.col("coarse_id").alias("old"))
        t = labels.select(F.col("id").alias("dst"), F.col("coarse_id").alias("new"))
        volume = graph.edges.join(t, "dst").groupBy(F.col("src").alias("id"), "new").agg(F.sum("w").alias("w"))
        reach = volume.join(movers, "id").join(weights.withColumnRenamed("coarse_id", "new"), "new", "left")
        room = reach.filter((F.col("new") == F.col("old")) | (F.col("full") + F.col("c") <= most))
        best = room.groupBy("id").agg(F.max_by(F.struct("new", "old", "c", "w", "full"), F.struct("w", -F.col("new"))).alias("b")).select("id", "b.*").filter("new <> old")
        before = F.sum("c").over(W.partitionBy("new").orderBy(F.desc("w"), "id"))
        moves = best.withColumn("upto", before).filter(F.col("full") + F.col("upto") <= most).select("id", "new")
        labels = barrier(labels.join(moves, "id", "left").select("id", F.coalesce("new", "coarse_id").alias("coarse_id")))
    # a label may name a vertex that has left: the least member stands for a cluster
    least = labels.groupBy("coarse_id").agg(F.min("id").alias("least"))
    return labels.join(least, "coarse_id").select("id", F.col("least").alias("coarse_id"))
