"""The refinement loop on the cluster.

Its rounds are steps over shards (taskmap.plans.rounds). Only graphs with a vertex of very many edges are refined by the loop
over rows, which is the rest of this module: a round ends in barriers, so plans never grow beyond one. What a round reads and writes follows the vertices that move: the
cost and the weights of the blocks are kept up by the moves alone (one small job, k rows to the driver); the connectivity is
a base table with the changes since, which are summed for the vertices asked for and put together every COMPACT rounds; and
every vertex's best move is kept, and only those of movers and their neighbours are computed anew. The mapping itself, two
numbers for each vertex, is written whole. What a round leaves behind goes when the next one doesn't need it.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap import objective as measures
from taskmap.config import Config
from taskmap.functions import kernels
from taskmap.functions.kernels import State, accepts, pass_config
from taskmap.graph import TaskGraph
from taskmap.operators import moves as lp
from taskmap.operators import rebalance as rb
from taskmap.plans.iterate import Clock, barrier, release, steady
from taskmap.plans.rounds import refine_shards
from taskmap.plans.shards import hubs
from taskmap.topology import MatrixTopology, Topology, load_bound, with_distance

#: Rounds after which the connectivity's changes are put together.
COMPACT = 6


def limits(spark: SparkSession, k: int, total: int, config: Config) -> DataFrame:
    """pe, part, bound, average for one part with k equal blocks."""
    bound = load_bound(total, k, config.eps_num, config.eps_den)
    row = spark.range(k).select(F.col("id").cast("int").alias("pe"), F.lit(0).alias("part"))
    return row.withColumn("bound", F.lit(bound).cast("long")).withColumn("average", F.lit(total // k).cast("long"))


@dataclass
class Volumes:
    """The connectivity id, pe, w: a table and changes to it."""

    base: DataFrame
    changes: list[DataFrame] = field(default_factory=list)

    def rows(self, only: DataFrame | None = None) -> DataFrame:
        """Of all vertices, or of those in only (id)."""
        parts = [p if only is None else p.join(only.select("id"), "id", "left_semi") for p in (self.base, *self.changes)]
        if len(parts) == 1:
            return parts[0]
        all_rows = parts[0]
        for p in parts[1:]:
            all_rows = all_rows.unionByName(p)
        return all_rows.groupBy("id", "pe").agg(F.sum("w").alias("w")).filter("w <> 0")

    def after(self, change: DataFrame) -> Volumes:
        new = Volumes(self.base, [*self.changes, barrier(change)])
        return new if len(new.changes) <= COMPACT else Volumes(barrier(new.rows()))


@dataclass
class Working:
    """Where the loop stands. best holds every vertex's best move but for those in stale, whose moves have to be computed anew."""

    mapping: DataFrame
    volumes: Volumes
    loads: dict[int, int]
    state: State
    best: DataFrame | None = None
    stale: list[DataFrame] = field(default_factory=list)

    def tables(self) -> list[DataFrame]:
        return [x for x in (self.mapping, self.volumes.base, *self.volumes.changes, self.best, *self.stale) if x is not None]


def _cost(graph: TaskGraph, mapping: DataFrame, topology: Topology | MatrixTopology) -> int:
    return measures.objective(graph, mapping, topology).head()["j"]


def _excess(loads: dict[int, int], bounds: dict[int, tuple[int, int, int]]) -> int:
    return max((loads.get(pe, 0) - bound for pe, (_, bound, _) in bounds.items()), default=0)


def _table(spark: SparkSession, loads: dict[int, int], bounds: dict[int, tuple[int, int, int]]) -> DataFrame:
    """pe, part, bound, average, weight: one row for each block."""
    rows = [(pe, part, bound, average, loads.get(pe, 0)) for pe, (part, bound, average) in sorted(bounds.items())]
    return spark.createDataFrame(rows, "pe int, part int, bound long, average long, weight long")


def _fitted(graph: TaskGraph, mapping: DataFrame, table: DataFrame) -> DataFrame:
    """The last resort of strong rebalancing: as in weak rebalancing, but every mover to the roomiest block of its part
    that can take it; one mover for each overloaded block and round, the heaviest that fits."""
    room = table.filter("weight < bound").groupBy("part").agg(F.max_by("pe", F.col("bound") - F.col("weight")).alias("pe_new"), F.max(F.col("bound") - F.col("weight")).alias("room"))
    over = table.filter("weight > bound").select("pe", "part")
    own = graph.vertices.join(mapping, "id").join(F.broadcast(over), "pe").join(F.broadcast(room), "part").filter("c <= room")
    best = own.groupBy("part").agg(F.max_by(F.struct("id", "pe", "pe_new"), F.struct("c", -F.col("id"))).alias("m"))
    return best.select("m.id", F.col("m.pe").alias("pe_old"), "m.pe_new", F.lit(0).cast("long").alias("gain"))


def _fresh(now: Working, topology: Topology | MatrixTopology) -> Working:
    """With the best moves of all vertices known."""
    if now.best is None:
        best = barrier(lp.best_moves(measures.gains(now.volumes.rows(), now.mapping, topology)))
    elif now.stale:
        changed = now.stale[0]
        for more in now.stale[1:]:
            changed = changed.unionByName(more)
        changed = barrier(changed.distinct()) if len(now.stale) > 1 else changed
        best = barrier(lp.refreshed(now.best, changed, now.volumes.rows(changed), now.mapping, topology))
    else:
        return now
    return Working(now.mapping, now.volumes, now.loads, now.state, best)


def _carried(graph: TaskGraph, now: Working, moves: DataFrame, change: int, shift: dict[int, int], bounds: dict) -> Working:
    """After the moves."""
    mapping = barrier(lp.apply_moves(now.mapping, moves))
    volumes = now.volumes.after(lp.connectivity_change(graph.edges, moves))
    loads = {pe: now.loads.get(pe, 0) + shift.get(pe, 0) for pe in {*now.loads, *shift}}
    excess = _excess(loads, bounds)
    stale = [*now.stale, barrier(lp.dirty(graph.edges, moves))] if now.best is not None else []
    return Working(mapping, volumes, loads, State(excess <= 0, now.state.j + change, excess), now.best, stale)


def refine(graph: TaskGraph, mapping: DataFrame, topology: Topology | MatrixTopology, blocks: DataFrame, config: Config, clock: Clock | None = None, level: int = 0) -> DataFrame:
    """id, pe: the best mapping that the loop meets. blocks(pe, part, bound, average) limit the weights.

    A graph below config.small_edges, of one part, is one task's work, like everywhere: the same loop over arrays.

    Balanced: label propagation. Otherwise weak rebalancing up to max_weak times in a row, then strong. A candidate counts
    if it is accepted (taskmap.functions.kernels.accepts); the loop goes on from the candidate all the same, and ends when
    `patience` rounds brought no improvement that counts.
    """
    clock = clock or Clock()
    bounds = {r["pe"]: (r["part"], r["bound"], r["average"]) for r in blocks.collect()}  # k rows
    if config.small_edges and len({part for part, _, _ in bounds.values()}) == 1 and graph.edges.count() <= config.small_edges:
        from taskmap.plans.multilevel import in_kernel

        bound, dist = np.array([bounds[pe][1] for pe in sorted(bounds)]), topology.dense()
        with clock.phase("refine", level):
            return barrier(in_kernel(graph, lambda g, pe, _: kernels.refine(g, pe, dist, bound, config), start=mapping))
    if not hubs(graph):
        return refine_shards(graph, mapping, bounds, topology.dense(), config, clock, level)
    return _refine_rows(graph, mapping, topology, bounds, config, clock, level)


def _refine_rows(graph: TaskGraph, mapping: DataFrame, topology: Topology | MatrixTopology, bounds: dict[int, tuple[int, int, int]], config: Config, clock: Clock, level: int) -> DataFrame:
    """The loop over rows, for graphs with a vertex whose edges no task should hold."""
    spark = graph.edges.sparkSession
    mapping = barrier(mapping)
    loads = {r["pe"]: r["weight"] for r in graph.vertices.join(mapping, "id").groupBy("pe").agg(F.sum("c").alias("weight")).collect()}  # k rows
    excess = _excess(loads, bounds)
    held = State(excess <= 0, _cost(graph, mapping, topology), excess)
    best = start = Working(mapping, Volumes(barrier(measures.connectivity(graph.edges, mapping))), loads, held)
    for p in range(config.passes):
        own = pass_config(config, p)
        now = start
        patience = weak = held_back = 0
        locked: DataFrame | None = None
        for r in range(config.rounds):
            if patience >= config.patience:
                break
            patience += 1
            before, waited = now, held_back
            with clock.phase("refine", level, round=r) as log:
                if now.state.feasible:
                    now = _fresh(now, topology)
                    moves = lp.label_propagation(graph.edges, now.volumes.rows(), now.mapping, topology, locked, own.filter_mode, own.relaxed_c, now.best)
                    moves, weak = barrier(moves), 0
                else:
                    table = _table(spark, now.loads, bounds)
                    run = rb.weak if weak < config.max_weak else rb.strong
                    moves = barrier(run(graph.vertices, now.volumes.rows(), now.mapping, table, topology, own).select("id", "pe_old", "pe_new", "gain"))
                    if run is rb.strong and not moves.limit(1).count():
                        moves = barrier(_fitted(graph, now.mapping, table))
                    weak = weak + 1 if run is rb.weak else 0
                if locked is not None:
                    release(locked)
                feasible = now.state.feasible
                count, change, shift = _told(graph, now.mapping, moves, topology)
                log["moved"] = count
                if count:
                    now = _carried(graph, now, moves, change, shift, bounds)
                locked, held_back = (moves, count) if feasible else (None, 0)
            take, anew = accepts(held, now.state, config.phi)
            past = [before, best]
            if take:
                best, held = now, now.state
            _drop(past, [best, now])
            if anew:
                patience = 0
            if not count and feasible and not waited and not anew:
                break  # nothing moves and nothing was locked: every further round is the same
        _drop([now], [best])
        start = best
    release(*(t for t in best.tables() if t is not best.mapping))
    return best.mapping


def _drop(past: list[Working], kept: list[Working]) -> None:
    """Deletes the tables of past states that no kept one has."""
    needed = [t for x in kept for t in x.tables()]
    release(*(t for x in past for t in x.tables() if not any(t is k for k in needed)))


def _told(graph: TaskGraph, mapping: DataFrame, moves: DataFrame, topology: Topology | MatrixTopology) -> tuple[int, int, dict[int, int]]:
    """How many moves, what they change of the cost, and of the blocks' weights: at most 2 k + 2 rows to the driver.

    Of the cost: the moves' own edges, twice where only one end moves, once where both do.
    """
    m = moves.select(F.col("id").alias("src"), F.col("pe_old").alias("s0"), F.col("pe_new").alias("s1"))
    there = mapping.select(F.col("id").alias("dst"), F.col("pe").alias("d0"))
    moved = moves.select(F.col("id").alias("dst"), F.col("pe_new").alias("d1"))
    near = graph.edges.join(m, "src").join(there, "dst").join(moved, "dst", "left")
    near = near.withColumns({"times": F.when(F.col("d1").isNull(), F.lit(2)).otherwise(F.lit(1)), "d1": F.coalesce("d1", "d0")})
    near = with_distance(with_distance(near, topology, "s0", "d0", "x0"), topology, "s1", "d1", "x1")
    row = lambda kind, pe, x: (F.lit(kind).alias("kind"), pe.cast("int").alias("pe"), x.cast("long").alias("x"))
    cost = near.agg(F.sum(F.col("times") * F.col("w") * (F.col("x1") - F.col("x0"))).alias("x")).select(*row("cost", F.lit(None), F.coalesce("x", F.lit(0))))
    ends = F.array(F.struct(F.col("pe_old").alias("pe"), (-F.col("c")).alias("c")), F.struct(F.col("pe_new").alias("pe"), F.col("c").alias("c")))
    loads = graph.vertices.join(moves, "id").select(F.explode(ends).alias("e")).groupBy("e.pe").agg(F.sum("e.c").alias("x")).select(*row("load", F.col("pe"), F.col("x")))
    number = moves.agg(F.count("*").alias("x")).select(*row("count", F.lit(None), F.col("x")))
    with steady(moves.sparkSession):
        rows = cost.unionByName(loads).unionByName(number).collect()
    one = {r["kind"]: r["x"] for r in rows if r["pe"] is None}
    return one["count"], one["cost"], {r["pe"]: r["x"] for r in rows if r["kind"] == "load"}
