"""Results stay whole where inputs pass a size that a method might be tempted to stop at."""

import datetime as dt

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from taskmap import metrics as me
from taskmap.config import DEEP_PASSES, Config
from taskmap.functions import kernels as kn
from taskmap.plans import baselines as bl
from taskmap.plans import experiments as ex
from taskmap.plans.iterate import barrier
from taskmap.queries import QUERIES, SQL, mappers
from taskmap.sources.generators import grid
from taskmap.streaming import edges as st
from taskmap.topology import Topology


def hot_window(tmp_path):
    """300 users in one window, some of them twice, one without a name, and three users in a later window."""
    start = dt.datetime(2024, 1, 1)
    rows = [(i, start + dt.timedelta(seconds=i), i % 300) for i in range(450)]
    rows += [(450, start, None)] + [(451 + i, start + dt.timedelta(minutes=30 + i), 7 * i) for i in range(3)]
    path = str(tmp_path / "events.parquet")
    con = duckdb.connect()
    con.execute("CREATE TABLE events (event_id BIGINT, ts TIMESTAMP, user_id BIGINT)")
    con.executemany("INSERT INTO events VALUES (?, ?, ?)", rows)
    con.execute(f"COPY events TO '{path}' (FORMAT parquet)")
    return con, path


def test_window_edges_of_a_hot_window(spark, tmp_path):
    con, path = hot_window(tmp_path)
    events = spark.read.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    for name, slide in (("window_edges_tumbling", None), ("window_edges_sliding", "5 minutes")):
        want = sorted(con.execute(f"SELECT CAST(epoch(start) AS BIGINT), a, b, w FROM ({SQL[name]})").fetchall())
        got = st.window_edges(events, "10 minutes", slide).select(F.col("start").cast("long"), "a", "b", "w")
        assert sorted(map(tuple, got.collect())) == want
    assert len(want) > 300 * 299 // 2


def test_serial_baseline_stays_serial(spark, monkeypatch):
    g = grid(spark, 8, 8)
    g = type(g)(barrier(g.vertices), barrier(g.edges))
    t, asked = Topology.parse("2:2", "1:10"), []
    start = barrier(g.vertices.selectExpr("id", "cast(id * 7 % 13 % 4 as int) as pe"))
    monkeypatch.setattr(bl, "multilevel_map", lambda graph, topology, config: asked.append(config) or start)
    pes = lambda m: [r["pe"] for r in m.orderBy("id").collect()]
    # on a graph above small_edges too, the serial pass follows, and no level goes to the distributed mapper
    config = Config(small_edges=100, eps_num=30)
    got = pes(bl.serial_integrated(g, t, "strong", config))
    assert got == pes(bl.sequential_lp(g, start, t, config, 20)) != pes(start)
    assert asked[0].small_edges > g.edges.count()


def undirected(n, pairs):
    a, b, w = np.array(pairs).T
    return kn.Small.of(np.arange(n), np.ones(n, int), np.concatenate((a, b)), np.concatenate((b, a)), np.concatenate((w, w)))[0]


def test_local_search_passes_through_a_loss():
    # 0 and 1 belong with 2 and 3, but each alone loses by going there
    g, flat = undirected(4, [(0, 1, 5), (0, 2, 3), (1, 2, 3), (2, 3, 20)]), np.ones((2, 2)) - np.eye(2)
    start, bound = np.array([0, 0, 1, 1]), np.array([4, 4])
    assert kn.edge_cut(g, kn.refine(g, start, flat, bound, Config())) == 6
    assert kn.edge_cut(g, kn.local_search(g, start, flat, bound)) == 0
    # without room for both there is no better prefix, and all moves are taken back
    assert (kn.local_search(g, start, flat, np.array([3, 3])) == start).all()


def test_local_search_on_random_graphs():
    rng = np.random.default_rng(1)
    for _ in range(20):
        n, k = int(rng.integers(8, 60)), int(rng.integers(2, 5))
        pairs = {(min(a, b), max(a, b)): int(rng.integers(1, 9)) for a, b in rng.integers(0, n, (3 * n, 2)) if a != b}
        g = undirected(n, [(a, b, w) for (a, b), w in pairs.items()])
        dist, bound, start = np.abs(np.subtract.outer(np.arange(k), np.arange(k))), np.full(k, -(-n // k) + 1), np.arange(n) % k
        pe = kn.local_search(g, start, dist, bound)
        assert np.bincount(pe, minlength=k).max() <= bound[0] and kn.objective(g, pe, dist) <= kn.objective(g, start, dist)
        assert (kn.local_search(g, pe, dist, bound) == pe).all()


def test_strong_multisection_has_the_local_search(monkeypatch):
    asked = []
    monkeypatch.setattr(bl, "multisection", lambda graph, topology, config: asked.append(config))
    bl.serial_multisection(None, Topology.parse("2:2", "1:10"), "strong", Config())
    i = np.arange(900)
    g = undirected(900, [(v, v + 1, 1) for v in i if v % 30 < 29] + [(v, v + 30, 1) for v in i if v < 870])
    flat, bound = np.ones((4, 4)) - np.eye(4), np.full(4, 231)
    pe = kn.partition(g, bound, asked[0])
    assert asked[0].local_search == "fm" and (kn.local_search(g, pe, flat, bound) == pe).all()


def test_registered_loops_have_the_settings_of_the_mappers(spark, tiny, monkeypatch):
    asked = {}

    def stop(name, at):
        def told(*args, **more):
            asked[name] = args[at] if len(args) > at else None, more
            raise InterruptedError

        return told

    monkeypatch.setattr(mappers, "refine", stop("refine", 4))
    monkeypatch.setattr(mappers.ml, "coarsen", stop("coarsen", 3))
    monkeypatch.setattr(mappers.mt, "heavy_edge_matching", stop("matching", 2))
    monkeypatch.setattr(mappers.mt, "cluster", stop("cluster", 2))
    wanted = {"refine_mapping": ("refine", Config()), "refine_deep": ("refine", Config(passes=DEEP_PASSES)), "refine_distributed": ("refine", Config(small_edges=0)), "coarsening_levels": ("coarsen", Config(small_edges=0)), "heavy_edge_matching": ("matching", Config()), "cluster_coarsen": ("cluster", None)}
    for query, (name, config) in wanted.items():
        with pytest.raises(InterruptedError):
            QUERIES[query](spark, tiny)
        assert asked[name] == (config, {})


def test_experiments_run_everything(spark, tiny):
    """All algorithms on a graph, a task for each run; the measures over them, ablations and phases."""
    rows = ex.runs(spark, tiny, ["mesh", "chain"], list(ex.KERNELS), ["2:2", "2:2:2"], 2).collect()
    assert len(rows) == 2 * len(ex.KERNELS) * 2 * 2 and {r["algorithm"] for r in rows} == set(ex.MAPPERS)
    assert all(r["j"] >= 2 * r["edge_cut"] >= 0 and r["seconds"] > 0 for r in rows)
    told = {r["algorithm"]: r for r in ex.summary(spark.createDataFrame([tuple(r) for r in rows], me.RUNS), "cut_only").collect()}
    assert told["cut_only"]["speedup"] == 1 and sum(r["n_best"] for r in told.values()) >= 4
    assert told["multisection"]["mean_excess"] < told["cut_only"]["mean_excess"]
    changes = ex.ablations(spark, tiny, ["mesh"], ["2:2"], 1).collect()
    assert [r["change"] for r in changes] == list(ex.ABLATIONS) and all(0.2 < r["geo_mean"] < 5 for r in changes)
    shares = ex.phases(spark, tiny, ["mesh"], "2:2:2").collect()
    assert {"coarsen", "contract", "initial", "refine", "uncontract"} == {r["phase"] for r in shares}
    assert sum(r["share"] for r in shares) == pytest.approx(1, abs=1e-4)


def test_kernels_of_the_experiments_are_the_mappers(spark, tiny):
    """A run in a task of its own gives the mapping's cost that the plan gives."""
    from taskmap import objective as ob
    from taskmap.sources.graphs import mesh

    built = mesh(spark, tiny)
    g = type(built)(barrier(built.vertices), barrier(built.edges))
    small, t = ex.arrays(g), Topology.parse("2:2:2", "1:10:100")
    for name in ("multisection", "integrated", "serial_multisection_fast", "serial_integrated_fast", "cut_only", "two_phase"):
        want = ob.objective(g, ex.MAPPERS[name](g, t, Config()), t).head()["j"]
        assert ex.measured(small, name, t, Config())[0] == want, name


def test_larger_graphs_are_mapped_by_the_plans(spark, tiny):
    rows = ex.runs(spark, tiny, ["mesh"], ["integrated"], ["2:2"], 1, Config(small_edges=100, rounds=2, patience=1)).collect()
    assert len(rows) == 1 and rows[0]["j"] > 0
