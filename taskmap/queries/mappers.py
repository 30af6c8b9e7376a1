"""Whole algorithms. Each answers with a certificate: size, feasibility, cover, and whether it beats the trivial mapping.

Certificates are literal in SQL, so a mapping that is infeasible, incomplete or no better than modulo fails the check.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap import objective as ob
from taskmap.config import DEEP_PASSES, Config
from taskmap.graph import TaskGraph
from taskmap.operators import matching as mt
from taskmap.operators.contraction import contract
from taskmap.plans import baselines as bl
from taskmap.plans import multilevel as ml
from taskmap.plans.iterate import barrier
from taskmap.plans.multisection import multisection
from taskmap.plans.refine import limits, refine
from taskmap.queries import text as q
from taskmap.sources import graphs as src
from taskmap.sources.graphs import trivial_mapping
from taskmap.topology import Topology, load_bound

QUERIES: dict = {}
SQL: dict = {}

T8, T32 = Topology.parse("2:2:2", "1:10:100"), Topology.parse("4:8:1", "1:10:100")
CONFIG = Config()


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """id, pe of the mesh on eight PEs by recursive multisection."""
    return multisection(src.mesh(spark, d), T8, CONFIG)


def held(g: TaskGraph) -> TaskGraph:
    return TaskGraph(barrier(g.vertices), barrier(g.edges))


def certificate(g: TaskGraph, mapping: DataFrame, t: Topology, config: Config = CONFIG, against: DataFrame | None = None) -> DataFrame:
    """k, n, feasible, covers_all, not_worse (than the modulo mapping, or the one given)."""
    k = t.k
    n, total = g.vertices.agg(F.count("*"), F.sum("c")).head()
    bound = load_bound(total, k, config.eps_num, config.eps_den)
    mapping = barrier(mapping)
    loads = ob.imbalance(g.vertices, mapping, k).select((F.col("max_block") <= bound).alias("feasible"))
    cover = mapping.join(g.vertices, "id").agg((F.count_distinct("id") == n).alias("a"), F.count("*").alias("c"), F.min("pe").alias("low"), F.max("pe").alias("high"))
    cover = cover.select((F.col("a") & (F.col("c") == n) & (F.col("low") >= 0) & (F.col("high") < k)).alias("covers_all"))
    base = ob.objective(g, against if against is not None else trivial_mapping(g.vertices, k), t).withColumnRenamed("j", "base")
    own = ob.objective(g, mapping, t).join(base).select((F.col("j") <= F.col("base")).alias("not_worse"))
    return loads.join(cover).join(own).select(F.lit(k).alias("k"), F.lit(n).cast("long").alias("n"), "feasible", "covers_all", "not_worse")


def certified(name: str, t: Topology, run, build=src.mesh, table: str = "part"):
    QUERIES[name] = lambda spark, d: certificate(g := held(build(spark, d)), run(g), t)
    SQL[name] = f"SELECT {t.k} AS k, count(*) AS n, TRUE AS feasible, TRUE AS covers_all, TRUE AS not_worse FROM {table}"


def points(spark: SparkSession, d: str) -> TaskGraph:
    return src.geometric(spark, d)


certified("map_multisection", T32, lambda g: multisection(g, T32, CONFIG))
certified("map_multisection_small", T8, lambda g: multisection(g, T8, CONFIG))
certified("map_multisection_deep", T32, lambda g: multisection(g, T32, CONFIG.but(passes=DEEP_PASSES)))
certified("map_multilevel", T32, lambda g: ml.multilevel_map(g, T32, CONFIG))
certified("map_multilevel_points", T8, lambda g: ml.multilevel_map(g, T8, CONFIG), points, "embeddings")
certified("partition_edge_cut", T32, lambda g: ml.partition_edge_cut(g, 32, CONFIG))
certified("partition_edge_cut_deep", T32, lambda g: ml.partition_edge_cut(g, 32, CONFIG.but(passes=DEEP_PASSES)))
certified("map_two_phase", T32, lambda g: bl.two_phase(g, T32, CONFIG))
for _preset in bl.PRESETS:
    certified(f"map_cpu_multisection_{_preset}", T32, lambda g, p=_preset: bl.serial_multisection(g, T32, p, CONFIG))
    certified(f"map_cpu_integrated_{_preset}", T32, lambda g, p=_preset: bl.serial_integrated(g, T32, p, CONFIG))
certified("initial_mapping", T32, lambda g: ml.initial_mapping(g, T32, g.vertices.agg(F.sum("c")).head()[0], CONFIG))
certified("initial_bisect", T32, lambda g: ml.initial_mapping(g, T32, g.vertices.agg(F.sum("c")).head()[0], CONFIG.but(initial="bisect")))
certified("initial_restarts", T32, lambda g: ml.initial_mapping(g, T32, g.vertices.agg(F.sum("c")).head()[0], CONFIG.but(restarts=3)))
certified("sequential_lp", T32, lambda g: bl.sequential_lp(g, trivial_mapping(g.vertices, 32), T32, CONFIG))


def _refined(g: TaskGraph, config: Config = CONFIG) -> DataFrame:
    """The loop from contiguous ranges, with the settings of the mappers."""
    n = g.vertices.count()
    start = trivial_mapping(g.vertices, 8, "range")
    return refine(g, start, T8, limits(g.vertices.sparkSession, 8, n, CONFIG), config)


certified("refine_mapping", T8, _refined)
certified("refine_deep", T8, lambda g: _refined(g, CONFIG.but(passes=DEEP_PASSES)))
#: On the cluster, whatever the graph's size, with the published patience; the cap of all rounds is ours.
certified("refine_distributed", T8, lambda g: _refined(g, CONFIG.but(small_edges=0)))


def map_multisection_fixed_eps(spark: SparkSession, d: str) -> DataFrame:
    """The original method: one imbalance for all splits, which may end above the bound; so only cover and cost are certified."""
    g = held(src.mesh(spark, d))
    return certificate(g, multisection(g, T32, CONFIG.but(adaptive=False)), T32).drop("feasible")


QUERIES["map_multisection_fixed_eps"] = map_multisection_fixed_eps
SQL["map_multisection_fixed_eps"] = "SELECT 32 AS k, count(*) AS n, TRUE AS covers_all, TRUE AS not_worse FROM part"


def heavy_edge_matching(spark: SparkSession, d: str) -> DataFrame:
    """n, involution (pairs of two), coverage_ok, weight_kept (by the contraction)."""
    g = held(src.mesh(spark, d))
    matched, n, done = mt.heavy_edge_matching(g, None, CONFIG)
    from taskmap.operators.contraction import completed

    pairs = matched.groupBy("coarse_id").agg(F.count("*").alias("m")).agg(F.coalesce(F.bool_and(F.col("m") == 2), F.lit(True)).alias("involution"))
    small = contract(g, completed(g.vertices, matched))
    kept = small.vertices.agg(F.sum("c").alias("c")).select((F.col("c") == n).alias("weight_kept"))
    return pairs.join(kept).select(F.lit(n).cast("long").alias("n"), "involution", F.lit(done > CONFIG.match_target * n).alias("coverage_ok"), "weight_kept")


QUERIES["heavy_edge_matching"] = heavy_edge_matching
SQL["heavy_edge_matching"] = "SELECT count(*) AS n, TRUE AS involution, TRUE AS coverage_ok, TRUE AS weight_kept FROM part"


def coarsening_levels(spark: SparkSession, d: str) -> DataFrame:
    """level, n, m, c_total of a forced distributed coarsening, down to the coarsest level."""
    g = held(src.mesh(spark, d))
    levels = ml.coarsen(g, None, 8 * 4, CONFIG.but(small_edges=0))
    rows = [x.graph.vertices.agg(F.lit(i).alias("level"), F.lit(x.n).cast("long").alias("n"), F.lit(x.m).cast("long").alias("m"), F.sum("c").alias("c_total")) for i, x in enumerate(levels)]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


QUERIES["coarsening_levels"] = coarsening_levels


def cluster_coarsen(spark: SparkSession, d: str) -> DataFrame:
    """n, covers_all, max_weight_ok, smaller of the clustering alternative."""
    g = held(src.overlap(spark, d))
    most = 20
    clusters = mt.cluster(g, most)
    small = contract(g, clusters)
    n = g.vertices.count()
    own = small.vertices.agg(F.sum("c").alias("c"), F.max("c").alias("top"), F.count("*").alias("m"))
    return own.select(F.lit(n).cast("long").alias("n"), (F.col("c") == n).alias("covers_all"), (F.col("top") <= most).alias("max_weight_ok"), (F.col("m") < n).alias("smaller"))


QUERIES["cluster_coarsen"] = cluster_coarsen
SQL["cluster_coarsen"] = "SELECT count(*) AS n, TRUE AS covers_all, TRUE AS max_weight_ok, TRUE AS smaller FROM documents"

#: The edges (u, v, w) of a worked example with eight tasks.
EIGHT = [(0, 1, 5), (2, 3, 5), (4, 5, 5), (6, 7, 5), (0, 2, 3), (1, 3, 3), (4, 6, 3), (5, 7, 3), (3, 4, 1), (7, 0, 2)]


def eight_tasks(spark: SparkSession) -> TaskGraph:
    return TaskGraph.from_pairs(spark.createDataFrame(EIGHT, "a long, b long, w long"))


def eight_groups(spark: SparkSession, d: str) -> TaskGraph:
    """Eight tasks: parts and suppliers by their keys modulo eight; w is the number of lines between two of them."""
    lines = src.load(spark, d, "lineitem", "l_partkey", "l_suppkey")
    every = spark.range(8).select("id", F.lit(1).cast("long").alias("c"))
    return TaskGraph.from_pairs(lines.select((F.col("l_partkey") % 8).alias("a"), (F.col("l_suppkey") % 8).alias("b")), every)


def exact_tiny(spark: SparkSession, d: str) -> DataFrame:
    return bl.exact_mapping(eight_groups(spark, d), Topology.parse("2:2", "1:10"), CONFIG)


_groups = "x AS (SELECT least(l_partkey % 8, l_suppkey % 8) AS u, greatest(l_partkey % 8, l_suppkey % 8) AS v, count(*) AS w FROM lineitem WHERE l_partkey % 8 <> l_suppkey % 8 GROUP BY 1, 2)"
_fits = " AND ".join("(" + " + ".join(f"CAST((i.range >> {2 * v}) & 3 = {b} AS INTEGER)" for v in range(8)) + ") <= 3" for b in range(4))
_digits = f"y AS (SELECT i.range AS m, (i.range >> (2 * u)) & 3 AS s, (i.range >> (2 * v)) & 3 AS t, w FROM range(65536) i CROSS JOIN x WHERE {_fits})"
QUERIES["exact_tiny"] = exact_tiny
SQL["exact_tiny"] = f"WITH {_groups}, {_digits} SELECT CAST(8 AS BIGINT) AS n, 4 AS k, CAST(min(j) AS BIGINT) AS best_j FROM (SELECT m, sum(2 * w * ({q.distance(Topology.parse('2:2', '1:10'), 's', 't')})) AS j FROM y GROUP BY m)"


def one_to_one_exact(spark: SparkSession, d: str) -> DataFrame:
    """As many tasks as PEs, one on each: the quadratic assignment problem, by trying all."""
    return bl.exact_mapping(eight_groups(spark, d), T8, CONFIG.but(eps_num=0))


_seats = " ".join(f"JOIN range(8) p{v} ON p{v}.range NOT IN ({', '.join(f'p{u}.range' for u in range(v))})" for v in range(1, 8))
_orders = f"o AS (SELECT [{', '.join(f'p{v}.range' for v in range(8))}] AS p FROM range(8) p0 {_seats})"
QUERIES["one_to_one_exact"] = one_to_one_exact
SQL["one_to_one_exact"] = f"WITH {_groups}, {_orders} SELECT CAST(8 AS BIGINT) AS n, 8 AS k, CAST(min(j) AS BIGINT) AS best_j FROM (SELECT p, sum(2 * w * ({q.distance(T8, 'p[u + 1]', 'p[v + 1]')})) AS j FROM o CROSS JOIN x GROUP BY p)"
