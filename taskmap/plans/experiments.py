"""The experiments, re-expressed on the given tables.

Each returns rows of runs (taskmap.metrics.RUNS) or of measures over them. Times leave out reading and building the graph,
which is materialised first, and writing the mapping.
"""

from __future__ import annotations

import json
import os
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from taskmap import metrics as me
from taskmap import objective as ob
from taskmap.config import DEEP_PASSES, Config
from taskmap.functions import kernels
from taskmap.graph import TaskGraph
from taskmap.plans import baselines as bl
from taskmap.plans.iterate import Clock, barrier, ensure_checkpoints
from taskmap.plans.multilevel import multilevel_map, partition_edge_cut
from taskmap.plans.multisection import multisection
from taskmap.sources.graphs import BUILDERS
from taskmap.topology import Topology, load_bound

HIERARCHIES = [f"4:8:{h}" for h in range(1, 7)]
DISTANCE = "1:10:100"
SEEDS = 5

Mapper = Callable[[TaskGraph, Topology, Config], DataFrame]
Kernel = Callable[[kernels.Small, Topology, Config], np.ndarray]

#: Own comparison, then the serial baselines, then the edge-cut partitioner as a mapper.
MAPPERS: dict[str, Mapper] = {
    "multisection": lambda g, t, c: multisection(g, t, c),
    "multisection_deep": lambda g, t, c: multisection(g, t, c.but(passes=DEEP_PASSES)),
    "integrated": lambda g, t, c: multilevel_map(g, t, c),
    "serial_multisection_strong": lambda g, t, c: bl.serial_multisection(g, t, "strong", c),
    "serial_multisection_fast": lambda g, t, c: bl.serial_multisection(g, t, "fast", c),
    "serial_integrated_strong": lambda g, t, c: bl.serial_integrated(g, t, "strong", c),
    "serial_integrated_fast": lambda g, t, c: bl.serial_integrated(g, t, "fast", c),
    "cut_only": lambda g, t, c: partition_edge_cut(g, t.k, c),
    "cut_only_deep": lambda g, t, c: partition_edge_cut(g, t.k, c.but(passes=DEEP_PASSES)),
    "two_phase": lambda g, t, c: bl.two_phase(g, t, c),
}
OWN = ["multisection", "multisection_deep", "integrated"]
SERIAL = [*OWN, "serial_multisection_strong", "serial_multisection_fast", "serial_integrated_strong", "serial_integrated_fast"]
CUT_ONLY = ["integrated", "cut_only", "cut_only_deep"]

#: Ablations: changes of the configuration against the default, for the mapper named.
ABLATIONS: dict[str, tuple[str, dict]] = {
    "filter_relaxed": ("integrated", {"filter_mode": "relaxed"}),
    "rebalance_by_cost": ("integrated", {"rebalance_objective": "comm"}),
    "rating_by_weight": ("integrated", {"rating": "weight"}),
    "fixed_imbalance": ("multisection", {"adaptive": False}),
    "clustering": ("integrated", {"coarsening": "cluster"}),
}
#: A run of an experiment is one task's work up to so many times Config.small_edges: dozens of runs of a graph go side by side,
#: where on the cluster they would go one after another. The kernels hold a graph of that size in a few hundred MB.
RUN_TIMES = 5
#: The same, where the tasks map the graph's arrays from files in the folder that executors share, so that neither the driver
#: nor a broadcast holds them. A kernel of 7,000,000 edges then has its coarser levels and a round's tables in memory.
FILE_TIMES = 25
#: Runs that take longest begin first.
SLOW = ("serial_multisection_strong", "multisection_deep", "cut_only_deep", "serial_integrated_strong")
#: Points of the performance profile, by the excess in percent.
TAUS = {"0": 1.0, "5": 1.05, "20": 1.2, "50": 1.5, "100": 2.0}


def machine(hierarchy: str) -> Topology:
    """With as many distances as the hierarchy has levels."""
    return Topology.parse(hierarchy, ":".join(DISTANCE.split(":")[: hierarchy.count(":") + 1]))


def _serial(preset: str, rounds: int) -> Kernel:
    def run(g: kernels.Small, t: Topology, c: Config) -> np.ndarray:
        own = c.but(**bl.PRESETS[preset])
        bound = np.full(t.k, load_bound(int(g.c.sum()), t.k, c.eps_num, c.eps_den))
        return kernels.sequential_lp(g, kernels.integrated(g, t, own), t.dense(), bound, own, rounds)

    return run


def _cut_only(g: kernels.Small, t: Topology, c: Config) -> np.ndarray:
    return kernels.integrated(g, Topology.flat(t.k), c.but(filter_mode="relaxed"))


def _two_phase(g: kernels.Small, t: Topology, c: Config) -> np.ndarray:
    blocks = _cut_only(g, t, c)
    volume = np.zeros((t.k, t.k))
    np.add.at(volume, (blocks[g.src], blocks[g.dst]), g.w)
    np.fill_diagonal(volume, 0)
    return kernels.place_blocks(volume, t.dense().astype(float))[blocks]


#: What the mappers do with a graph below Config.small_edges, in one task.
KERNELS: dict[str, Kernel] = {
    "multisection": lambda g, t, c: kernels.multisection(g, t, c),
    "multisection_deep": lambda g, t, c: kernels.multisection(g, t, c.but(passes=DEEP_PASSES)),
    "integrated": lambda g, t, c: kernels.integrated(g, t, c),
    "serial_multisection_strong": lambda g, t, c: kernels.multisection(g, t, c.but(**bl.PRESETS["strong"], local_search=bl.SEARCH["strong"])),
    "serial_multisection_fast": lambda g, t, c: kernels.multisection(g, t, c.but(**bl.PRESETS["fast"])),
    "serial_integrated_strong": _serial("strong", 20),
    "serial_integrated_fast": _serial("fast", 3),
    "cut_only": _cut_only,
    "cut_only_deep": lambda g, t, c: _cut_only(g, t, c.but(passes=DEEP_PASSES)),
    "two_phase": _two_phase,
}


def measured(g: kernels.Small, algorithm: str, t: Topology, config: Config) -> tuple[int, int, int, float]:
    """Cost, edge-cut, heaviest block and CPU seconds of a run."""
    began = time.process_time()
    pe = KERNELS[algorithm](g, t, config)
    seconds = time.process_time() - began
    return kernels.objective(g, pe, t.dense()), kernels.edge_cut(g, pe), int(np.bincount(pe, weights=g.c, minlength=t.k).max()), seconds


def arrays(g: TaskGraph, config: Config = Config()) -> kernels.Small | None:
    """The graph as arrays on the driver, if a run of it is one task's work."""
    if g.edges.count() > RUN_TIMES * config.small_edges:
        return None
    v, e = (x.toPandas() for x in (g.vertices, g.edges))
    return kernels.Small.of(*(x.to_numpy() for x in (v["id"], v["c"], e["src"], e["dst"], e["w"])))[0]


def filed(g: TaskGraph, config: Config = Config()) -> dict[str, str] | None:
    """Files of the graph's arrays, if a run of it is one task's work and the folder for checkpoints is one of plain files."""
    spark = g.vertices.sparkSession
    ensure_checkpoints(spark)
    shared = spark._jvm.org.apache.hadoop.fs.Path(spark.sparkContext._jsc.sc().getCheckpointDir().get()).toUri()
    if shared.getScheme() not in (None, "file") or g.edges.count() > FILE_TIMES * config.small_edges:
        return None
    folder = f"{shared.getPath()}/arrays-{uuid.uuid4().hex}"

    def written(df: DataFrame, known: str | None) -> str:
        """A folder with a file for each column, from one task in the order of rows; vertices are numbered in the order known."""

        def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = f"{folder}/{uuid.uuid4().hex}"  # of this attempt
            os.makedirs(own)
            ids = None if known is None else mapped(f"{known}/id")
            files = {name: open(f"{own}/{name}", "wb") for name in names}  # noqa: SIM115
            for batch in batches:
                for name, column in zip(names, batch.columns):
                    x = column.to_numpy(zero_copy_only=False).astype(np.int64)
                    files[name].write((x if ids is None or name == "w" else np.searchsorted(ids, x)).tobytes())
            for f in files.values():
                f.close()
            yield pa.record_batch([pa.array([own])], ["path"])

        names = df.columns
        return df.repartition(1).sortWithinPartitions(*names[:-1]).mapInArrow(task, "path string").head()["path"]

    vertices = written(g.vertices.select("id", "c"), None)
    edges = written(g.edges.select("src", "dst", "w"), vertices)
    return {"folder": folder, "c": f"{vertices}/c", **{name: f"{edges}/{name}" for name in ("src", "dst", "w")}}


def mapped(path: str) -> np.ndarray:
    return np.asarray(np.memmap(path, np.int64, "r")) if os.path.getsize(path) else np.zeros(0, np.int64)


def spread(spark: SparkSession, small: kernels.Small | dict[str, str], jobs: list[tuple], run: Callable[[kernels.Small, tuple], list[tuple]], schema: str) -> DataFrame:
    """Rows of run(graph, job) for all jobs, a job for each task. The graph is broadcast, or mapped from its files.

    The first jobs begin first.
    """
    shared = spark.sparkContext.broadcast(small)
    listed = spark.createDataFrame([(i, json.dumps(j)) for i, j in enumerate(jobs)], "number int, job string")

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = pa.schema([(f.name, {"string": pa.string(), "int": pa.int32(), "bigint": pa.int64(), "double": pa.float64()}[f.dataType.simpleString()]) for f in fields])
        graph = shared.value
        if isinstance(graph, dict):
            graph = kernels.Small(*(mapped(graph[name]) for name in ("c", "src", "dst", "w")))
        for batch in batches:
            rows = [row for job in batch.column("job").to_pylist() for row in run(graph, json.loads(job))]
            yield from pa.Table.from_pylist([dict(zip(kinds.names, r)) for r in rows], schema=kinds).to_batches()

    fields = T._parse_datatype_string(schema).fields
    return listed.repartitionByRange(len(jobs), "number").mapInArrow(task, schema)


def runs(spark: SparkSession, folder: str, graphs: list[str], algorithms: list[str], hierarchies: list[str] = HIERARCHIES, seeds: int = 1, config: Config = Config()) -> DataFrame:
    """RUNS: one row for each graph, hierarchy, algorithm and seed; seconds are CPU seconds of the algorithm alone."""
    return variants(spark, folder, graphs, {"": (algorithms, {})}, hierarchies, seeds, config).drop("change")


def variants(spark: SparkSession, folder: str, graphs: list[str], changes: dict[str, tuple[list[str], dict]], hierarchies: list[str] = HIERARCHIES, seeds: int = 1, config: Config = Config()) -> DataFrame:
    """RUNS and change, for each change of the configuration: the algorithms to run, and what is changed.

    Runs of one graph are independent: up to FILE_TIMES times config.small_edges each is a task of its own, so the cluster runs
    many at once; larger graphs are mapped by the distributed plans one after another (wall seconds then).
    """
    schema = me.RUNS + ", change string"
    jobs = [(a, h, s, name) for name, (algorithms, _) in changes.items() for a in algorithms for h in hierarchies for s in range(seeds)]
    jobs.sort(key=lambda j: (SLOW.index(j[0]) if j[0] in SLOW else len(SLOW), -machine(j[1]).k))
    changed = {name: change for name, (_, change) in changes.items()}
    out, folders = None, []
    for name in graphs:
        built = BUILDERS[name](spark, folder)
        g = TaskGraph(barrier(built.vertices), barrier(built.edges))
        small = arrays(g, config) or filed(g, config)

        def one(small: kernels.Small, job: tuple, name: str = name) -> list[tuple]:
            algorithm, h, seed, change = job
            return [(algorithm, name, h, seed, small.n, *measured(small, algorithm, machine(h), config.but(seed=seed, **changed[change])), change)]

        if small is not None:
            rows = spread(spark, small, jobs, one, schema)
        else:
            rows = spark.createDataFrame([(*_distributed(g, name, a, h, s, config.but(**changed[change])), change) for a, h, s, change in jobs], schema)
        out = rows if out is None else out.unionByName(rows)
        if isinstance(small, dict):
            folders.append(small["folder"])
    out = barrier(out)
    for folder in folders:
        path = spark._jvm.org.apache.hadoop.fs.Path(f"file://{folder}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return out


def _distributed(g: TaskGraph, name: str, algorithm: str, h: str, seed: int, config: Config) -> tuple:
    t = machine(h)
    began = time.perf_counter()
    mapping = barrier(MAPPERS[algorithm](g, t, config.but(seed=seed)))
    seconds = time.perf_counter() - began
    j = ob.objective(g, mapping, t).head()["j"]
    cut = ob.edge_cut(g, mapping).head()["cut"]
    top = ob.imbalance(g.vertices, mapping, t.k).head()["max_block"]
    return algorithm, name, h, seed, g.vertices.count(), j, cut, top, seconds


def comparison(spark: SparkSession, folder: str, graphs: list[str], algorithms: list[str], base: str, hierarchies: list[str] = HIERARCHIES, seeds: int = SEEDS) -> DataFrame:
    """A row for each algorithm: its share of best costs, excess over the best, and speedup over the base."""
    return summary(runs(spark, folder, graphs, algorithms, hierarchies, seeds), base)


def summary(rows: DataFrame, base: str) -> DataFrame:
    """algorithm, n_instances, n_best, share, mean_excess, worst_ratio, speedup (of CPU seconds over the base, geometric mean)
    and share_within_<tau>: the performance profile at a few points."""
    means = barrier(me.seed_average(rows))
    out = me.best_share(means).join(me.excess_over_best(means), "algorithm")
    out = out.join(me.speedups(means, base).select("algorithm", F.col("geo_mean").alias("speedup")), "algorithm")
    profile = me.performance_profile(means, list(TAUS.values()))
    for name, tau in TAUS.items():
        out = out.join(profile.filter(F.col("tau") == tau).select("algorithm", F.col("share").alias(f"share_within_{name}")), "algorithm")
    return out


def ablations(spark: SparkSession, folder: str, graphs: list[str], hierarchies: list[str] = HIERARCHIES, seeds: int = SEEDS) -> DataFrame:
    """change, mapper, n_instances, geo_mean, least, most: the cost with a change over that without, both means over seeds."""
    changes = {"": (sorted({a for a, _ in ABLATIONS.values()}), {})} | {name: ([a], change) for name, (a, change) in ABLATIONS.items()}
    rows = variants(spark, folder, graphs, changes, hierarchies, seeds)
    usual = barrier(me.seed_average(rows.filter("change = ''")))
    out = None
    for name in ABLATIONS:
        other = me.seed_average(rows.filter(F.col("change") == name))
        both = other.select("algorithm", "instance", "hierarchy", F.col("j").alias("other")).join(usual, ["algorithm", "instance", "hierarchy"])
        ratio = F.try_divide("other", "j")
        row = both.groupBy("algorithm").agg(F.count("*").alias("n_instances"), me.geo_mean(ratio).alias("geo_mean"), F.round(F.min(ratio), 6).alias("least"), F.round(F.max(ratio), 6).alias("most"))
        row = row.select(F.lit(name).alias("change"), F.col("algorithm").alias("mapper"), "n_instances", "geo_mean", "least", "most")
        out = row if out is None else out.unionByName(row)
    return out


def phases(spark: SparkSession, folder: str, graphs: list[str], hierarchy: str = "4:8:6", seeds: int = 1, config: Config = Config()) -> DataFrame:
    """instance, phase, seconds, share: where the integrated mapper's time goes; means over seeds."""
    out = None
    for name in graphs:
        built = BUILDERS[name](spark, folder)
        g, t = TaskGraph(barrier(built.vertices), barrier(built.edges)), machine(hierarchy)
        small = arrays(g, config)

        def one(small: kernels.Small, job: tuple, name: str = name, t: Topology = t) -> list[tuple]:
            spent: dict[str, float] = {}
            kernels.integrated(small, t, config.but(seed=job[0]), spent=spent)
            return [(name, phase, seconds) for phase, seconds in spent.items()]

        if small is not None:
            rows = spread(spark, small, [(s,) for s in range(seeds)], one, "instance string, phase string, seconds double")
        else:
            clock = Clock()
            multilevel_map(g, t, config, clock)
            rows = spark.createDataFrame([(name, phase, float(s)) for phase, s in clock.seconds().items()], "instance string, phase string, seconds double")
        out = rows if out is None else out.unionByName(rows)
    sums = barrier(out).groupBy("instance", "phase").agg(F.round(F.avg("seconds"), 6).alias("seconds"))
    return sums.withColumn("share", F.round(F.col("seconds") / F.sum("seconds").over(W.partitionBy("instance")), 6))


def layout(spark: SparkSession, folder: str, graph: str = "mesh", k: int = 32) -> dict[str, float]:
    """Seconds of the connectivity from edge rows, and from neighbour lists that are exploded again."""
    from taskmap.sources.graphs import trivial_mapping

    built = BUILDERS[graph](spark, folder)
    edges, m = barrier(built.edges), barrier(trivial_mapping(built.vertices, k))
    lists = barrier(edges.groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("near")))
    out = {}
    for name, e in (("edge_rows", edges), ("neighbour_lists", lists.select("src", F.explode("near").alias("x")).select("src", "x.dst", "x.w"))):
        began = time.perf_counter()
        ob.connectivity(e, m).write.format("noop").mode("overwrite").save()
        out[name] = time.perf_counter() - began
    return out


def report(spark: SparkSession, folder: str, graphs: list[str] | None = None, hierarchies: list[str] = HIERARCHIES, seeds: int = SEEDS) -> Iterator[dict]:
    """All experiments: every graph and machine, five seeds, and the phases of each graph on the largest machine."""
    graphs = graphs or list(BUILDERS)
    every = runs(spark, folder, graphs, list(KERNELS), hierarchies, seeds)
    yield from ({"experiment": "runs", **r.asDict()} for r in every.collect())
    for name, algorithms, base in (("own", OWN, "multisection_deep"), ("serial", SERIAL, "serial_multisection_strong"), ("cut_only", CUT_ONLY, "cut_only")):
        for r in summary(every.filter(F.col("algorithm").isin(algorithms)), base).collect():
            yield {"experiment": name, **r.asDict()}
    for r in ablations(spark, folder, graphs, hierarchies, seeds).collect():
        yield {"experiment": "ablation", **r.asDict()}
    for r in phases(spark, folder, graphs, hierarchies[-1]).collect():
        yield {"experiment": "phases", **r.asDict()}
    yield {"experiment": "layout", **layout(spark, folder)}
