"""Steps over many shards against the one-task kernels, in one job and as jobs of their own, and the plans over rows beside them."""

import numpy as np
import pytest

from taskmap.config import Config
from taskmap.functions import kernels as kn
from taskmap.operators import matching as mt
from taskmap.operators.contraction import completed
from taskmap.plans import refine as rf
from taskmap.plans import shards
from taskmap.plans.refine import limits, refine
from taskmap.topology import load_bound
from tests.test_distributed import T, both, held, partition_of


@pytest.mark.parametrize("border", [10**6, 0])
@pytest.mark.parametrize("start, change", [("modulo", {"filter_mode": "relaxed", "passes": 2}), ("one", {}), ("one", {"rebalance_objective": "comm", "sigma_mode": "absolute", "sigma_gap": 1})])
def test_refinement_over_shards_is_the_kernel(spark, monkeypatch, border, start, change):
    monkeypatch.setattr(shards, "WORTH", 100)
    monkeypatch.setattr(shards, "BORDER", border)
    n, config = 80, Config(rounds=6, small_edges=0, **change)
    g, small = both(spark, n, 100, 3)
    at = {"modulo": np.arange(n) % 8, "one": np.where(np.arange(n) < 60, 0, np.arange(n) % 8)}[start]
    first = spark.createDataFrame([(i, int(p)) for i, p in enumerate(at)], "id long, pe int")
    assert shards.Shards(g, "pe", first.withColumnRenamed("pe", "value")).count > 1
    want = kn.refine(small, at.astype(np.int64), T.dense(), np.full(8, load_bound(n, 8, 3, 100)), config)
    assert (held(refine(g, first, T, limits(spark, 8, n, config), config)) == want).all()


@pytest.mark.parametrize("border", [10**6, 0])
def test_matching_over_shards_is_the_kernel(spark, monkeypatch, border):
    monkeypatch.setattr(shards, "WORTH", 100)
    monkeypatch.setattr(shards, "BORDER", border)
    g, small = both(spark, 150, 400, 5, heavy=3)
    matched, n, done = mt.heavy_edge_matching(g, 1000, Config())
    assert done == matched.count() and partition_of(held(completed(g.vertices, matched), "coarse_id")) == partition_of(kn.matching(small, 1000, Config()))


def test_a_graph_with_a_hub_keeps_to_rows(spark, monkeypatch):
    monkeypatch.setattr(shards, "HUB", 3)
    monkeypatch.setattr(rf, "refine_shards", None)
    n, config = 40, Config(rounds=2, small_edges=0)
    g, small = both(spark, n, 60, 3)
    first = spark.createDataFrame([(i, i % 8) for i in range(n)], "id long, pe int")
    want = kn.refine(small, np.arange(n) % 8, T.dense(), np.full(8, load_bound(n, 8, 3, 100)), config)
    assert (held(refine(g, first, T, limits(spark, 8, n, config), config)) == want).all()
