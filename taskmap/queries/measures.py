"""Costs of mappings, and measures that compare algorithms over instances."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap import metrics as me
from taskmap import objective as ob
from taskmap.queries import text as q
from taskmap.queries.steps import T32, T192, mod
from taskmap.sources import graphs as src
from taskmap.topology import Topology

QUERIES: dict = {}
SQL: dict = {}


def here(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


PLACED = f"WITH {q.graph('copurchase')}, {q.mapping()}, {q.PLACED}"
COST = f"w * ({q.distance(T32, 'pe_s', 'pe_d')})"


@here("objective_j", f"{PLACED} SELECT CAST(sum({COST}) AS BIGINT) AS j FROM pl")
def objective_j(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return ob.objective(g, mod(g), T32)


@here("objective_j_192", f"WITH {q.graph('mesh')}, {q.mapping('mod', 192)}, {q.PLACED} SELECT CAST(sum(w * ({q.distance(T192, 'pe_s', 'pe_d')})) AS BIGINT) AS j FROM pl")
def objective_j_192(spark: SparkSession, d: str) -> DataFrame:
    g = src.mesh(spark, d)
    return ob.objective(g, mod(g, 192), T192)


@here("edge_cut", f"{PLACED} SELECT CAST(sum(w) AS BIGINT) AS cut FROM pl WHERE src < dst AND pe_s <> pe_d")
def edge_cut(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return ob.edge_cut(g, mod(g))


@here("quotient_graph", f"{PLACED} SELECT pe_s AS pe_x, pe_d AS pe_y, CAST(sum(w) AS BIGINT) AS w FROM pl WHERE pe_s <> pe_d GROUP BY pe_s, pe_d")
def quotient_graph(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return ob.quotient(g, mod(g))


WIDE = ", ".join(f"CAST(coalesce(sum(w) FILTER (pe_d = {y}), 0) AS BIGINT) AS to_{y}" for y in range(8))


@here("quotient_pivot", f"WITH {q.graph('copurchase')}, {q.mapping('mod', 8)}, {q.PLACED} SELECT pe_s AS pe_x, {WIDE} FROM pl WHERE pe_s <> pe_d GROUP BY pe_s")
def quotient_pivot(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return ob.quotient_pivot(g, mod(g, 8), 8)


@here("j_by_level", f"{PLACED}, lv AS (SELECT CAST({q.level(T32, 'pe_s', 'pe_d')} AS INTEGER) AS level, w, {COST} AS x FROM pl) SELECT level, CAST(sum(w) AS BIGINT) AS w, CAST(sum(x) AS BIGINT) AS cost FROM lv GROUP BY ROLLUP(level)")
def j_by_level(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return ob.objective_by_level(g, mod(g), T32)


@here("block_loads", f"WITH {q.parts('size')}, {q.mapping()}, {q.blocks(32)} SELECT pe, weight, weight > bound AS overloaded FROM b")
def block_loads(spark: SparkSession, d: str) -> DataFrame:
    v = src.parts(spark, d, "size")
    return ob.block_loads(v, src.trivial_mapping(v, 32), 32, 3, 100)


@here("imbalance", f"WITH {q.parts('size')}, {q.mapping()}, {q.blocks(32)} SELECT max(weight) AS max_block, round(32 * max(weight) / sum(weight) - 1, 6) AS imbalance FROM b")
def imbalance(spark: SparkSession, d: str) -> DataFrame:
    v = src.parts(spark, d, "size")
    return ob.imbalance(v, src.trivial_mapping(v, 32), 32)


# a set of runs: three trivial mappings of the mesh on three machines, with times that stand for clocks

MACHINES = {"4:8:1": 32, "4:8:2": 64, "4:8:3": 96}
KINDS = {"mod": 4.0, "range": 2.0, "hash": 1.0}


def _pe(kind: str, k: int) -> str:
    return {"mod": f"id % {k}", "range": f"id * {k} // (SELECT count(*) FROM v)", "hash": f"{q.noise('id', 'id')} % {k}"}[kind]


def _runs_sql() -> str:
    rows = []
    for h, k in MACHINES.items():
        t = Topology.parse(h, "1:10:100")
        for kind, seconds in KINDS.items():
            m = f"(SELECT id, {_pe(kind, k)} AS pe FROM v)"
            j = f"(SELECT CAST(sum(e.w * ({q.distance(t, 's.pe', 't.pe')})) AS BIGINT) FROM e JOIN {m} s ON s.id = e.src JOIN {m} t ON t.id = e.dst)"
            for seed in (0, 1):
                rows.append(f"SELECT '{kind}' AS algorithm, 'mesh' AS instance, '{h}' AS hierarchy, {seed} AS seed, (SELECT count(*) FROM v) AS n, {j} AS j, CAST({seconds * k / 32 + seed} AS DOUBLE) AS seconds")
    means = "means AS (SELECT algorithm, instance, hierarchy, max(n) AS n, avg(j) AS j, avg(seconds) AS seconds FROM runs GROUP BY algorithm, instance, hierarchy), wb AS (SELECT *, min(j) OVER (PARTITION BY instance, hierarchy) AS best FROM means)"
    return f"{q.graph('mesh')}, runs AS ({' UNION ALL '.join(rows)}), {means}"


RUNS = _runs_sql()


def runs(spark: SparkSession, d: str) -> DataFrame:
    g = src.mesh(spark, d)
    n = g.vertices.count()
    out = []
    for h, k in MACHINES.items():
        for kind, seconds in KINDS.items():
            j = ob.objective(g, src.trivial_mapping(g.vertices, k, kind), Topology.parse(h, "1:10:100"))
            own = j.select(F.lit(kind).alias("algorithm"), F.lit("mesh").alias("instance"), F.lit(h).alias("hierarchy"), F.explode(F.array(F.lit(0), F.lit(1))).alias("seed"), F.lit(n).cast("long").alias("n"), "j")
            out.append(own.withColumn("seconds", F.lit(seconds * k / 32) + F.col("seed")))
    return reduce(DataFrame.unionByName, out)


@here("seed_average", f"WITH {RUNS} SELECT algorithm, instance, hierarchy, n, round(j, 6) AS j, round(seconds, 6) AS seconds FROM means")
def seed_average(spark: SparkSession, d: str) -> DataFrame:
    return me.seed_average(runs(spark, d)).withColumns({"j": F.round("j", 6), "seconds": F.round("seconds", 6)})


TAUS = [1.0, 1.05, 1.1, 2.0, 5.0, 20.0]


@here("performance_profile", f"WITH {RUNS} SELECT algorithm, tau, round(avg(CASE WHEN j <= tau * best THEN 1.0 ELSE 0.0 END), 6) AS share FROM wb, (SELECT CAST(unnest({TAUS}) AS DOUBLE) AS tau) GROUP BY algorithm, tau")
def performance_profile(spark: SparkSession, d: str) -> DataFrame:
    return me.performance_profile(me.seed_average(runs(spark, d)), TAUS)


@here("best_share", f"WITH {RUNS} SELECT algorithm, CAST(count(*) FILTER (j = best) AS BIGINT) AS n_best, count(*) AS n_instances, round(avg(CASE WHEN j = best THEN 1.0 ELSE 0.0 END), 6) AS share FROM wb GROUP BY algorithm")
def best_share(spark: SparkSession, d: str) -> DataFrame:
    return me.best_share(me.seed_average(runs(spark, d)))


@here("excess_over_best", f"WITH {RUNS} SELECT algorithm, round(avg(j / best) - 1, 6) AS mean_excess, round(max(j / best), 6) AS worst_ratio FROM wb GROUP BY algorithm")
def excess_over_best(spark: SparkSession, d: str) -> DataFrame:
    return me.excess_over_best(me.seed_average(runs(spark, d)))


@here("speedups", f"WITH {RUNS}, x AS (SELECT a.algorithm, b.seconds / a.seconds AS x FROM means a JOIN means b USING (instance, hierarchy) WHERE b.algorithm = 'mod') SELECT algorithm, round(exp(avg(ln(x))), 6) AS geo_mean, round(min(x), 6) AS least, round(max(x), 6) AS most FROM x GROUP BY algorithm")
def speedups(spark: SparkSession, d: str) -> DataFrame:
    return me.speedups(me.seed_average(runs(spark, d)), "mod")


@here("pairwise_wins", f"WITH {RUNS}, x AS (SELECT CASE WHEN a.n < 1000000 THEN 'small' ELSE 'large' END AS size_class, a.j < b.j AS bj, a.seconds < b.seconds AS bs FROM means a JOIN means b USING (instance, hierarchy) WHERE a.algorithm = 'range' AND b.algorithm = 'mod') SELECT size_class, count(*) AS n, CAST(count(*) FILTER (bj) AS BIGINT) AS better_j, CAST(count(*) FILTER (bs) AS BIGINT) AS faster FROM x GROUP BY ROLLUP(size_class)")
def pairwise_wins(spark: SparkSession, d: str) -> DataFrame:
    return me.pairwise_wins(me.seed_average(runs(spark, d)), "range", "mod")


# a log of phases: kinds of events, of the users with even and with odd ids; values in whole hundredths add up the same in any order

PHASES = ["click", "error", "purchase", "signup", "view"]
PHASE_SQL = "log AS (SELECT event_type AS phase, CASE WHEN user_id % 2 = 0 THEN 'even' ELSE 'odd' END AS instance, round(value * 100) AS seconds FROM events)"


def phase_log(spark: SparkSession, d: str) -> DataFrame:
    events = src.load(spark, d, "events", "event_type", "user_id", "value")
    instance = F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd")
    return events.select(F.col("event_type").alias("phase"), instance.alias("instance"), F.round(F.col("value") * 100).alias("seconds"))


@here("phase_shares", f"WITH {PHASE_SQL} SELECT phase, round(sum(seconds), 6) AS seconds, round(sum(seconds) / sum(sum(seconds)) OVER (), 6) AS share FROM log WHERE instance = 'odd' GROUP BY phase")
def phase_shares(spark: SparkSession, d: str) -> DataFrame:
    return me.phase_shares(phase_log(spark, d).filter("instance = 'odd'"))


@here("phase_table", f"WITH {PHASE_SQL} SELECT instance, " + ", ".join(f"round(sum(seconds) FILTER (phase = '{p}'), 6) AS {p}" for p in PHASES) + " FROM log GROUP BY instance")
def phase_table(spark: SparkSession, d: str) -> DataFrame:
    return me.phase_table(phase_log(spark, d), PHASES)
