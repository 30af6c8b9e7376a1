"""Experiments at larger tables: a run is one task's work, and its tables of vertices by blocks come in portions."""

import tracemalloc

import numpy as np
import pytest
from test_mappers import grid

from taskmap.config import Config
from taskmap.functions import kernels as kn
from taskmap.plans import experiments as ex
from taskmap.topology import Topology, load_bound


def test_proposals_in_portions_are_those_of_the_whole_table(monkeypatch):
    g, t = grid(30, 40), Topology.parse("2:2:2", "1:10:100")
    pe = np.minimum(np.arange(g.n) * 8 // g.n, np.arange(g.n) % 40 // 5)
    for config in (Config(), Config(filter_mode="relaxed")):
        target, gain = kn.propose(kn.connectivity(g, pe, 8), pe, t.dense().astype(float), None, config)
        for table in (1 << 21, 64):
            monkeypatch.setattr(kn, "TABLE", table)
            got, told = kn.proposals(g, pe, g.rows(), t.dense().astype(float), None, config)
            assert (got == target).all() and (told[got >= 0] == gain[got >= 0]).all()


@pytest.mark.parametrize("objective", ["cut", "comm"])
@pytest.mark.parametrize("strong", [False, True])
def test_rebalancing_in_portions(monkeypatch, objective, strong):
    g, t = grid(30, 40), Topology.parse("2:2:2", "1:10:100")
    pe, bound = np.minimum(np.arange(g.n) * 10 // g.n, 7), np.full(8, load_bound(1200, 8, 3, 100))
    once, often = (monkeypatch.setattr(kn, "TABLE", table) or kn.rebalance(g, pe, g.rows(), t.dense().astype(float), bound, 150.0, Config(rebalance_objective=objective), strong) for table in (1 << 21, 64))
    assert len(once[0]) and all((a == b).all() for a, b in zip(once, often))


def test_a_refinement_holds_no_table_of_all_vertices():
    g, t = grid(200, 200), Topology.parse("4:8:6", "1:10:100")
    start = np.arange(g.n) * t.k // g.n
    tracemalloc.start()
    kn.refine(g, start, t.dense(), np.full(t.k, load_bound(g.n, t.k, 3, 100)), Config(patience=1, rounds=1))
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 2 * g.n * t.k * 8  # four and more of them before


def test_runs_above_the_kernels_size_are_tasks_too(spark, tiny, monkeypatch):
    built = ex.BUILDERS["mesh"](spark, tiny)
    edges = built.edges.count()
    config = Config(small_edges=edges - 1)
    monkeypatch.setattr(ex, "_distributed", lambda *a: pytest.fail("one after another"))
    rows = ex.variants(spark, tiny, ["mesh"], {"": (["integrated"], {}), "cluster": (["integrated"], {"coarsening": "cluster"})}, ["2:2"], 2, config).collect()
    assert sorted((r["change"], r["seed"]) for r in rows) == [("", 0), ("", 1), ("cluster", 0), ("cluster", 1)]
    small, t = ex.arrays(built, config), Topology.parse("2:2", "1:10")
    for r in rows:
        own = config.but(seed=r["seed"], coarsening=r["change"] or "matching")
        assert r["j"] == kn.objective(small, kn.integrated(small, t, own), t.dense())
    assert ex.arrays(built, Config(small_edges=edges // (ex.RUN_TIMES + 1))) is None
