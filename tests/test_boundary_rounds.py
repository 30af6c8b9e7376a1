"""Kernels' rounds look at the vertices between blocks, not at all edges."""

import heapq
from types import SimpleNamespace

import numpy as np
import pytest
from test_mappers import grid

from taskmap.config import Config
from taskmap.functions import kernels as kn
from taskmap.plans import experiments as ex
from taskmap.topology import Topology, load_bound

T = Topology.parse("4:8:1", "1:10:100")


def test_a_refinement_sums_all_edges_once(monkeypatch):
    g, calls, real = grid(60, 60), [], kn.objective
    monkeypatch.setattr(kn, "objective", lambda *a: calls.append(1) or real(*a))
    kn.refine(g, np.arange(g.n) * 32 // g.n, T.dense(), np.full(32, load_bound(g.n, 32, 3, 100)), Config(passes=3))
    assert len(calls) == 1  # one a round before


def test_matching_sorts_no_edges(monkeypatch):
    monkeypatch.setattr(kn, "_best_by", lambda *a: pytest.fail("sorted"))
    assert kn.matching(grid(40, 50), 2000, Config()).max() < 1300


@pytest.mark.parametrize("seed", range(4))
def test_a_front_is_what_counting_again_gives(seed):
    rng, g, dist = np.random.default_rng(seed), grid(30, 30), T.dense().astype(float)
    front = kn.Front(g, rng.integers(0, 32, g.n), dist, g.rows())
    for _ in range(5):
        v = np.sort(rng.choice(g.n, 200, replace=False))
        front.move(v, rng.integers(0, 32, 200))
        again = kn.Front(g, front.pe, dist, g.rows())
        assert front.j == again.j and (front.load == again.load).all() and (front.away == again.away).all()


@pytest.mark.parametrize("mode", ["nonnegative", "relaxed"])
def test_moves_over_the_blocks_touched_are_those_of_the_whole_table(mode):
    g, dist, config = grid(30, 40), T.dense().astype(float), Config(filter_mode=mode)
    pe = np.arange(g.n) * 32 // g.n
    target, gain = kn.propose(kn.connectivity(g, pe, 32), pe, dist, None, config)
    v, to, told = kn._few_blocks(g, pe, g.rows(), dist, np.arange(g.n), config)
    assert (v == np.flatnonzero(target >= 0)).all() and (to == target[v]).all() and (told == gain[v]).all()


def test_a_pass_of_the_local_search_ends_when_no_later_prefix_can_be_better(monkeypatch):
    g, pops = grid(60, 60), []
    monkeypatch.setattr(kn, "heapq", SimpleNamespace(heappush=heapq.heappush, heappop=lambda q: pops.append(1) or heapq.heappop(q)))
    start = (np.arange(g.n) % 60 >= 30).astype(np.int64)  # a straight cut
    got = kn.local_search(g, start, 1 - np.eye(2), np.full(2, 1854))
    assert kn.edge_cut(g, got) <= kn.edge_cut(g, start) and np.bincount(got).max() <= 1854
    assert len(pops) < 5000  # 7,241 when passes went on to their end


def test_runs_of_large_graphs_map_files(spark, tiny, monkeypatch):
    monkeypatch.setattr(ex, "_distributed", lambda *a: pytest.fail("one after another"))
    built = ex.BUILDERS["mesh"](spark, tiny)
    config = Config(small_edges=built.edges.count() // (ex.RUN_TIMES + 1))
    assert ex.arrays(built, config) is None
    rows = ex.runs(spark, tiny, ["mesh"], ["integrated", "multisection"], ["2:2"], 1, config).collect()
    small, t = ex.arrays(built), Topology.parse("2:2", "1:10")
    want = {name: kn.objective(small, getattr(kn, name)(small, t, config), t.dense()) for name in ("integrated", "multisection")}
    assert {r["algorithm"]: r["j"] for r in rows} == want and all(r["n"] == small.n for r in rows)
