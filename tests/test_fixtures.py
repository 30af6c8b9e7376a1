"""Worked examples whose numbers were computed without this engine."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from taskmap import metrics as me
from taskmap import objective as ob
from taskmap.config import Config
from taskmap.functions import kernels as kn
from taskmap.graph import TaskGraph
from taskmap.operators import contraction as ct
from taskmap.operators import matching as mt
from taskmap.operators import moves as lp
from taskmap.operators import rebalance as rb
from taskmap.plans.iterate import barrier
from taskmap.plans.refine import limits
from taskmap.queries.mappers import EIGHT, eight_tasks
from taskmap.topology import MatrixTopology, Topology, load_bound

TWO, THREE = Topology.parse("2:2", "1:10"), Topology.parse("2:2:2", "1:10:100")


def mapping(spark, pes):
    return spark.createDataFrame(list(enumerate(pes)), "id long, pe int")


def rows(df, *columns):
    return sorted(tuple(r[c] for c in columns) for r in df.collect())


@pytest.fixture(scope="module")
def eight(spark):
    return eight_tasks(spark).persist()


@pytest.mark.parametrize(
    "topology, pes, j",
    [
        (THREE, range(8), 880),
        (THREE, [0, 4, 1, 5, 2, 6, 3, 7], 4624),
        (TWO, [0, 0, 1, 1, 2, 2, 3, 3], 84),
        (Topology.flat(4), [0, 1, 0, 1, 2, 3, 2, 3], 46),
    ],
)
def test_costs_of_eight_tasks(spark, eight, topology, pes, j):
    m = mapping(spark, pes)
    assert ob.objective(eight, m, topology).head()["j"] == j
    matrix = MatrixTopology.of(topology.matrix(spark))
    assert ob.objective(eight, m, matrix).head()["j"] == j


def test_contraction_keeps_costs_and_weights(spark, eight):
    rating = mt.rated(eight.edges, eight.vertices)
    assert {(r["src"], r["dst"]): r["rating"] for r in rating.collect()}[0, 1] == 25
    matched = mt.mutual_pairs(mt.preferences(rating))
    assert rows(matched, "id", "coarse_id") == [(i, i - i % 2) for i in range(8)]
    small = ct.contract(eight, ct.completed(eight.vertices, matched))
    assert rows(small.vertices, "id", "c") == [(0, 2), (2, 2), (4, 2), (6, 2)]
    assert rows(small.edges.filter("src < dst"), "src", "dst", "w") == [(0, 2, 6), (0, 6, 2), (2, 4, 1), (4, 6, 6)]
    coarse = spark.createDataFrame([(0, 0), (2, 1), (4, 2), (6, 3)], "id long, pe int")
    assert ob.objective(small, coarse, TWO).head()["j"] == 84


def test_one_round_of_label_propagation(spark, eight):
    m = mapping(spark, [0, 1, 0, 1, 2, 3, 2, 3])
    conn = barrier(ob.connectivity(eight.edges, m))
    proposals = barrier(lp.propose(conn, m, TWO))
    assert rows(proposals, "id", "pe_new", "gain") == [(0, 1, 2), (1, 0, 2), (2, 1, 2), (3, 0, 2), (4, 3, 2), (5, 2, 2), (6, 3, 2), (7, 2, 2)]
    again = lp.reevaluated(eight.edges, proposals, m, TWO)
    assert rows(again, "id", "regain") == [(0, 2), (1, -8), (2, 8), (3, -2), (4, 2), (5, -8), (6, 8), (7, -2)]
    moves = barrier(lp.label_propagation(eight.edges, conn, m, TWO))
    after = barrier(lp.apply_moves(m, moves))
    assert [r[1] for r in rows(after, "id", "pe")] == [1, 1, 1, 1, 3, 3, 3, 3]
    assert ob.objective(eight, after, TWO).head()["j"] == 60
    assert ob.edge_cut(eight, after).head()["cut"] == 3
    delta = lp.update_connectivity(conn, eight.edges, moves)
    assert rows(delta, "id", "pe", "w") == rows(ob.connectivity(eight.edges, after), "id", "pe", "w")
    # vertices that touch only their own block propose nothing
    assert {r[0] for r in rows(ob.gains(ob.connectivity(eight.edges, after), after, TWO), "id")} == {0, 3, 4, 7}


def test_rebalancing(spark, eight):
    config = Config()
    m = mapping(spark, [1, 1, 1, 1, 3, 3, 3, 3])
    conn = barrier(ob.connectivity(eight.edges, m))
    blocks = barrier(rb.block_table(eight.vertices, m, limits(spark, 4, 8, config)))
    assert rows(blocks, "pe", "weight", "bound") == [(0, 0, 3), (1, 4, 3), (2, 0, 3), (3, 4, 3)]
    weak = rb.weak(eight.vertices, conn, m, blocks, TWO, config)
    assert rows(weak, "id", "gain", "bucket") == [(0, -10, 5), (4, -9, 5)] or [r[0] for r in rows(weak, "id")] == [0, 4]
    assert not rb.weak(eight.vertices, conn, m, blocks, TWO, config.but(sigma_mode="absolute")).count()
    strong = rb.strong(eight.vertices, conn, m, blocks, TWO, config)
    assert rows(strong, "id", "pe_new") == [(0, 0), (4, 0)]
    after = barrier(lp.apply_moves(m, strong))
    assert [r[1] for r in rows(after, "id", "pe")] == [0, 1, 1, 1, 0, 3, 3, 3]
    assert ob.objective(eight, after, TWO).head()["j"] == 218


@pytest.mark.parametrize("total, k, bound", [(8, 4, 3), (2000, 32, 65), (2000, 192, 11), (51183, 32, 1648), (51183, 192, 275), (4652, 32, 150)])
def test_load_bound(total, k, bound):
    assert load_bound(total, k, 3, 100) == bound


@pytest.mark.parametrize("part, k_part, levels, eps", [(96000, 96, 3, 0.0099016), (32100, 32, 2, 0.0133071), (31900, 32, 2, 0.0164786), (4050, 4, 1, 0.0172840)])
def test_adaptive_imbalance(part, k_part, levels, eps):
    assert kn.adaptive_eps(96000, part, 96, k_part, 0.03, levels) == pytest.approx(eps, abs=5e-7)


def test_two_hop_matching(spark):
    pairs = [(0, 1), (0, 2), (0, 3), (5, 7), (5, 8), (6, 7), (6, 8), (0, 7)]
    g = TaskGraph.from_pairs(spark.createDataFrame(pairs, "a long, b long"))
    none = spark.createDataFrame([], "id long, coarse_id long")
    assert rows(mt.match_leaves(g, none), "id", "coarse_id") == [(1, 1), (2, 1)]
    assert (5, 5) in rows(mt.match_twins(g, none), "id", "coarse_id") and (6, 5) in rows(mt.match_twins(g, none), "id", "coarse_id")


@pytest.mark.parametrize("x, y, d", [(0, 0, 0), (0, 3, 1), (0, 4, 10), (0, 32, 100), (5, 69, 100)])
def test_distances(x, y, d):
    t = Topology.parse("4:8:6", "1:10:100")
    assert t.k == 192 and t.dense()[x, y] == d
    assert Topology.from_json(t.to_json()) == t


def test_quality_measures(spark):
    js = {"a": [10, 20, 30], "b": [11, 18, 33], "c": [20, 20, 30]}
    runs = spark.createDataFrame([(a, f"i{i}", "h", 0, 10, j, None, None, 1.0) for a, x in js.items() for i, j in enumerate(x)], me.RUNS)
    means = me.seed_average(runs)
    shares = {(r["algorithm"], r["tau"]): r["share"] for r in me.performance_profile(means, [1, 1.1, 2]).collect()}
    assert shares["a", 1.0] == pytest.approx(2 / 3, abs=1e-6) and shares["b", 1.1] == 1 and shares["c", 2.0] == 1
    excess = {r["algorithm"]: (r["mean_excess"], r["worst_ratio"]) for r in me.excess_over_best(means).collect()}
    assert excess == {"a": (0.037037, 1.111111), "b": (0.066667, 1.1), "c": (0.37037, 2.0)}


def _small():
    a = np.array(EIGHT)
    s, t, w = (np.concatenate(x) for x in ((a[:, 0], a[:, 1]), (a[:, 1], a[:, 0]), (a[:, 2], a[:, 2])))
    return kn.Small.of(np.arange(8), np.ones(8, int), s, t, w)[0]


def test_kernels_reach_the_optimum_of_eight_tasks():
    g = _small()
    bound = np.full(4, 3)
    assert kn.exact(g, 4, TWO.dense(), bound)[0] == 84
    for run in (kn.multisection, kn.integrated):
        pe = run(g, TWO, Config())
        assert kn.objective(g, pe, TWO.dense()) == 84 and np.bincount(pe).max() <= 3


def test_gain_is_half_of_the_change(spark, eight):
    rng = np.random.default_rng(1)
    g, dist = _small(), THREE.dense()
    for _ in range(50):
        pe = rng.integers(0, 8, 8)
        conn = kn.connectivity(g, pe, 8)
        cost = conn @ dist
        v, b = rng.integers(0, 8, 2)
        new = pe.copy()
        new[v] = b
        assert kn.objective(g, pe, dist) - kn.objective(g, new, dist) == 2 * (cost[v, pe[v]] - cost[v, b])


def test_places_blocks_one_to_one():
    volume = np.zeros((8, 8))
    for u, v, w in EIGHT:
        volume[u, v] = volume[v, u] = w
    pe = kn.place_blocks(volume, THREE.dense().astype(float))
    assert sorted(pe) == list(range(8))
    assert (volume * THREE.dense()[np.ix_(pe, pe)]).sum() <= 4624


def test_validation_finds_violations(spark):
    v = spark.createDataFrame([(0, 1), (1, 0), (1, 1)], "id long, c long")
    e = spark.createDataFrame([(0, 1, 1), (1, 0, 2), (0, 0, 1), (0, 7, -1)], "src long, dst long, w long")
    from taskmap.graph import validation

    found = {r["check"]: r["violations"] for r in validation(TaskGraph(v, e)).collect()}
    assert found == {"asymmetric": 3, "endpoint_unknown": 0, "loop": 1, "nonpositive_c": 1, "nonpositive_w": 1, "pair_twice": 0, "vertex_twice": 1}
    with pytest.raises(ValueError):
        MatrixTopology.of(spark.createDataFrame([(0, 0, 0), (0, 1, 1), (1, 0, 2), (1, 1, 0)], "pe_x int, pe_y int, d long"))
    assert F is not None
