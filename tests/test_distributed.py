"""The distributed steps against the one-task kernels: the same definitions, so the same results, vertex by vertex."""

import numpy as np
import pytest

from taskmap import objective as ob
from taskmap.config import Config
from taskmap.functions import kernels as kn
from taskmap.graph import TaskGraph
from taskmap.operators import matching as mt
from taskmap.operators.contraction import completed
from taskmap.plans import multilevel as ml
from taskmap.plans.iterate import barrier
from taskmap.plans.multisection import multisection
from taskmap.plans.refine import limits, refine
from taskmap.topology import Topology, load_bound

T = Topology.parse("2:2:2", "1:10:100")


def both(spark, n, m, seed, heavy=1):
    """A random connected graph as tables and as arrays; ids are 0 to n - 1."""
    rng = np.random.default_rng(seed)
    pairs = {(i, i + 1): int(rng.integers(1, 9)) for i in range(n - 1)}
    for a, b in rng.integers(0, n, (m, 2)):
        if a != b:
            pairs[min(int(a), int(b)), max(int(a), int(b))] = int(rng.integers(1, 9))
    c = rng.integers(1, heavy + 1, n)
    v = spark.createDataFrame([(i, int(x)) for i, x in enumerate(c)], "id long, c long")
    g = TaskGraph.from_pairs(spark.createDataFrame([(a, b, w) for (a, b), w in pairs.items()], "a long, b long, w long"), v)
    g = TaskGraph(barrier(g.vertices), barrier(g.edges))
    a, b, w = np.array([(a, b, 2 * w // 2) for (a, b), w in pairs.items()]).T
    return g, kn.Small.of(np.arange(n), c, np.concatenate((a, b)), np.concatenate((b, a)), np.concatenate((w, w)))[0]


def held(mapping, column="pe"):
    return np.array([r[column] for r in mapping.orderBy("id").collect()])


@pytest.mark.parametrize("start, change", [("modulo", {"filter_mode": "relaxed"}), ("one", {}), ("one", {"rebalance_objective": "comm", "sigma_mode": "absolute", "sigma_gap": 1})])
def test_refinement_is_the_kernel(spark, start, change):
    """From balanced and from hopeless starts: rounds, locks, weak and strong rebalancing, changes put together."""
    n, config = 80, Config(rounds=6, small_edges=0, **change)
    g, small = both(spark, n, 100, 3)
    at = {"modulo": np.arange(n) % 8, "one": np.where(np.arange(n) < 60, 0, np.arange(n) % 8)}[start]
    want = kn.refine(small, at.astype(np.int64), T.dense(), np.full(8, load_bound(n, 8, 3, 100)), config)
    first = spark.createDataFrame([(i, int(p)) for i, p in enumerate(at)], "id long, pe int")
    got = refine(g, first, T, limits(spark, 8, n, config), config)
    assert (held(got) == want).all()
    assert (held(refine(g, first, T, limits(spark, 8, n, config), config.but(small_edges=10**6))) == want).all()
    assert ob.objective(g, got, T).head()["j"] == kn.objective(small, want, T.dense())


def partition_of(labels):
    return sorted(tuple(np.flatnonzero(labels == x)) for x in np.unique(labels))


@pytest.mark.parametrize("m, bound", [(60, 4), (400, 1000)])
def test_matching_is_the_kernel(spark, m, bound):
    config = Config()
    g, small = both(spark, 150, m, 5, heavy=3)
    matched, _, _ = mt.heavy_edge_matching(g, bound, config)
    got = held(completed(g.vertices, matched), "coarse_id")
    assert partition_of(got) == partition_of(kn.matching(small, bound, config))


def test_clustering_is_the_kernel(spark):
    config = Config(cluster_rounds=4)
    g, small = both(spark, 150, 300, 6, heavy=3)
    got = held(mt.cluster(g, 20, 4, config.seed), "coarse_id")
    want = kn.clustering(small, 20, config)
    assert partition_of(got) == partition_of(want) and np.bincount(want, weights=small.c).max() <= 20 and want.max() < 149


@pytest.mark.parametrize("coarsening, run", [("cluster", ml.multilevel_map), ("matching", multisection)])
def test_whole_mappers(spark, coarsening, run):
    """Nothing above the limit goes to a kernel; results are sound and about as good as the kernel's."""
    n, t = 60, Topology.parse("2:2", "1:10")
    g, small = both(spark, n, 50, 8)
    config = Config(small_edges=0, rounds=2, patience=1, match_rounds=2, cluster_rounds=3, coarsest_factor=8, coarsening=coarsening)
    kernel = kn.objective(small, kn.integrated(small, t, config), t.dense())
    m = barrier(run(g, t, config))
    assert m.count() == n and m.select("id").distinct().count() == n
    assert ob.imbalance(g.vertices, m, 4).head()["max_block"] <= load_bound(n, 4, 3, 100)
    assert ob.objective(g, m, t).head()["j"] <= 1.5 * kernel


def test_coarsening_that_stalls(spark):
    """A star cannot be matched: clusters go on where pairs end, and what is left starts scattered, not in one task."""
    n, t = 120, Topology.parse("2:2", "1:10")
    star = spark.range(1, n).selectExpr("0L as a", "id as b", "1L as w")
    g = TaskGraph.from_pairs(star, spark.range(n).selectExpr("id", "1L as c"))
    g = TaskGraph(barrier(g.vertices), barrier(g.edges))
    config = Config(small_edges=0, rounds=3, patience=1, match_rounds=1, cluster_rounds=2, coarsest_factor=2)
    m = barrier(ml.multilevel_map(g, t, config))
    assert m.count() == n and ob.imbalance(g.vertices, m, 4).head()["max_block"] <= load_bound(n, 4, 3, 100)
    assert ml.scattered(g, 4).select("pe").distinct().count() == 4
