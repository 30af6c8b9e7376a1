"""Topology, graphs, matching, contraction, moves and rebalancing, one step each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap import graph as gr
from taskmap import objective as ob
from taskmap.config import Config
from taskmap.graph import TaskGraph
from taskmap.operators import contraction as ct
from taskmap.operators import matching as mt
from taskmap.operators import moves as lp
from taskmap.operators import rebalance as rb
from taskmap.plans import multisection as ms
from taskmap.plans.iterate import barrier
from taskmap.plans.refine import limits
from taskmap.queries import text as q
from taskmap.sources import graphs as src
from taskmap.topology import MatrixTopology, Topology, floor_div, from_nation, load_bound_column

QUERIES: dict = {}
SQL: dict = {}

T32, T192 = Topology.parse("4:8:1", "1:10:100"), Topology.parse("4:8:6", "1:10:100")
CONFIG = Config()


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def mod(g: TaskGraph, k: int = 32) -> DataFrame:
    return src.trivial_mapping(g.vertices, k)


def total(g: TaskGraph) -> int:
    return g.vertices.agg(F.sum("c")).head()[0]


# topology


@query("pe_coordinates", "SELECT CAST(pe AS INTEGER) AS pe, CAST(pe // 4 AS INTEGER) AS l1, CAST(pe // 32 AS INTEGER) AS l2, CAST(pe // 192 AS INTEGER) AS l3, n FROM (SELECT l_partkey % 192 AS pe, count(*) AS n FROM lineitem GROUP BY 1)")
def pe_coordinates(spark: SparkSession, d: str) -> DataFrame:
    """Each PE that has parts of order lines, with its components and the number of lines."""
    used = src.load(spark, d, "lineitem", "l_partkey").groupBy((F.col("l_partkey") % 192).cast("int").alias("pe")).agg(F.count("*").alias("n"))
    at = T192.coords("pe")
    return used.select("pe", *[at[i].alias(f"l{i + 1}") for i in range(3)], "n")


PAIRS = f"SELECT CAST(x AS INTEGER) AS pe_x, CAST(y AS INTEGER) AS pe_y, n, CAST({q.distance(T32, 'x', 'y')} AS BIGINT) AS d FROM (SELECT l_partkey % 32 AS x, l_suppkey % 32 AS y, count(*) AS n FROM lineitem GROUP BY 1, 2)"


def line_traffic(spark: SparkSession, d: str) -> DataFrame:
    """pe_x, pe_y, n: the lines between the PE of the part and the PE of the supplier."""
    lines = src.load(spark, d, "lineitem", "l_partkey", "l_suppkey")
    at = lambda key, name: (F.col(key) % 32).cast("int").alias(name)
    return lines.groupBy(at("l_partkey", "pe_x"), at("l_suppkey", "pe_y")).agg(F.count("*").alias("n"))


@query("pe_distance", PAIRS)
def pe_distance(spark: SparkSession, d: str) -> DataFrame:
    return line_traffic(spark, d).withColumn("d", T32.distance("pe_x", "pe_y"))


@query("pe_matrix", PAIRS)
def pe_matrix(spark: SparkSession, d: str) -> DataFrame:
    given = MatrixTopology.of(T32.matrix(spark))
    return given.lookup(line_traffic(spark, d), "pe_x", "pe_y")


@query("nation_topology", "SELECT CAST(row_number() OVER (ORDER BY n_regionkey, n_nationkey) - 1 AS INTEGER) AS pe, n_name AS nation, r_name AS region, CAST(n_regionkey AS INTEGER) AS l1, 0 AS l2 FROM nation JOIN region ON r_regionkey = n_regionkey")
def nation_topology(spark: SparkSession, d: str) -> DataFrame:
    return from_nation(src.load(spark, d, "nation"), src.load(spark, d, "region"))


@query("load_bound", f"SELECT CAST(32 * (range + 1) AS INTEGER) AS k, CAST((SELECT sum(p_size) FROM part) AS BIGINT) AS total, CAST({q.bound('(SELECT sum(p_size) FROM part)', '(32 * (range + 1))')} AS BIGINT) AS bound FROM range(6)")
def load_bound_query(spark: SparkSession, d: str) -> DataFrame:
    sums = src.parts(spark, d, "size").agg(F.sum("c").alias("total"))
    own = sums.select(F.explode(F.array(*[F.lit(32 * h) for h in range(1, 7)])).alias("k"), "total")
    return own.withColumn("bound", load_bound_column(F.col("total"), F.col("k").cast("long"), 3, 100))


@query("flat_equals_cut", f"WITH {q.graph('mesh')}, {q.mapping()}, {q.PLACED} SELECT CAST(sum(CASE WHEN pe_s <> pe_d THEN w ELSE 0 END) AS BIGINT) AS j, CAST(sum(CASE WHEN pe_s <> pe_d THEN w ELSE 0 END) AS BIGINT) AS cut_twice FROM pl")
def flat_equals_cut(spark: SparkSession, d: str) -> DataFrame:
    g = src.mesh(spark, d)
    return ob.objective(g, mod(g), Topology.flat(32)).join(ob.edge_cut(g, mod(g)).select((2 * F.col("cut")).alias("cut_twice")))


# graphs

GRAPH_QUERIES = {"graph_copurchase": "copurchase", "graph_mesh": "mesh", "graph_line_adjacent": "line_adjacent", "graph_chain": "chain", "graph_colink": "colink", "geometric_graph": "geometric", "graph_coship": "coship", "graph_trade": "trade", "graph_handoff": "handoff", "graph_overlap": "overlap"}
for _name, _graph in GRAPH_QUERIES.items():
    query(_name, f"WITH {q.graph(_graph)} SELECT src, dst, w FROM e")(lambda spark, d, build=src.BUILDERS[_graph]: build(spark, d).edges)


@query("graph_validation", "SELECT unnest(['asymmetric', 'endpoint_unknown', 'loop', 'nonpositive_c', 'nonpositive_w', 'pair_twice', 'vertex_twice']) AS \"check\", CAST(0 AS BIGINT) AS violations")
def graph_validation(spark: SparkSession, d: str) -> DataFrame:
    return gr.validation(src.copurchase(spark, d))


DEGREES = "dg AS (SELECT v.id, v.c, CAST(count(e.src) AS BIGINT) AS deg, CAST(coalesce(sum(e.w), 0) AS BIGINT) AS wdeg FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id, v.c)"


@query("graph_degrees", f"WITH {q.graph('geometric')}, {DEGREES} SELECT id, deg, wdeg FROM dg")
def graph_degrees(spark: SparkSession, d: str) -> DataFrame:
    return gr.degrees(src.geometric(spark, d))


@query("graph_summary", f"WITH {q.graph('copurchase', 'size')}, {DEGREES} SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m, CAST(sum(wdeg) // 2 AS BIGINT) AS w_total, CAST(sum(c) AS BIGINT) AS c_total, max(deg) AS max_deg, CAST(count(*) FILTER (deg = 0) AS BIGINT) AS isolated FROM dg")
def graph_summary(spark: SparkSession, d: str) -> DataFrame:
    return gr.summary(src.copurchase(spark, d, "size"))


@query("trivial_mod", f"WITH {q.parts()}, {q.mapping()} SELECT id, pe FROM m")
def trivial_mod(spark: SparkSession, d: str) -> DataFrame:
    return src.trivial_mapping(src.parts(spark, d), 32)


@query("trivial_ranges", f"WITH {q.parts()}, {q.mapping('range')} SELECT id, pe FROM m")
def trivial_ranges(spark: SparkSession, d: str) -> DataFrame:
    return src.trivial_mapping(src.parts(spark, d), 32, "range")


RANGES = f"{q.graph('copurchase')}, {q.mapping('range', 8)}, {q.PLACED}"


@query("subgraph_sizes", f"WITH {RANGES} SELECT m.pe AS part, count(*) AS n, CAST(sum(c) AS BIGINT) AS w, CAST((SELECT count(*) FROM pl WHERE src < dst AND pe_s = m.pe AND pe_d = m.pe) AS BIGINT) AS m FROM v JOIN m ON m.id = v.id GROUP BY m.pe")
def subgraph_sizes(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return gr.subgraph_sizes(g, src.trivial_mapping(g.vertices, 8, "range"))


@query("subgraph_edges", f"WITH {RANGES} SELECT pe_s AS part, src, dst, w FROM pl WHERE pe_s = pe_d")
def subgraph_edges(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return gr.split_by_block(g, src.trivial_mapping(g.vertices, 8, "range"))[1].select("part", "src", "dst", "w")


@query("subgraph_renumber", f"WITH {q.parts()}, {q.mapping('mod', 8)} SELECT id, pe AS part, CAST(row_number() OVER (PARTITION BY pe ORDER BY id) - 1 AS BIGINT) AS new_id FROM m")
def subgraph_renumber(spark: SparkSession, d: str) -> DataFrame:
    part = src.trivial_mapping(src.parts(spark, d), 8).withColumnRenamed("pe", "part")
    return gr.dense_ids(part, "id", "part").select("id", "part", "new_id")


# matching and contraction

WEIGHTED = f"{q.graph('mesh', 'size')}, {q.RATED}"
ONE_ROUND = f"{WEIGHTED}, {q.prefs()}, {q.mutual()}"


def weighted(spark: SparkSession, d: str) -> tuple[TaskGraph, DataFrame]:
    g = src.mesh(spark, d, "size")
    return g, mt.rated(g.edges, g.vertices)


def one_round(spark: SparkSession, d: str) -> tuple[TaskGraph, DataFrame]:
    g, rating = weighted(spark, d)
    return g, mt.mutual_pairs(mt.preferences(rating))


@query("edge_rating", f"WITH {WEIGHTED} SELECT src, dst, round(rating, 6) AS rating FROM rt")
def edge_rating(spark: SparkSession, d: str) -> DataFrame:
    return weighted(spark, d)[1].select("src", "dst", F.round("rating", 6).alias("rating"))


@query("edge_rating_weight", f"WITH {q.graph('copurchase')} SELECT src, dst, CAST(w AS DOUBLE) AS rating FROM e")
def edge_rating_weight(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    return mt.rated(g.edges, g.vertices, "weight").select("src", "dst", "rating")


@query("edge_noise", f"WITH {WEIGHTED} SELECT src, dst, CAST(noise AS BIGINT) AS noise FROM rt")
def edge_noise(spark: SparkSession, d: str) -> DataFrame:
    return weighted(spark, d)[1].select("src", "dst", "noise")


@query("preferred_neighbor", f"WITH {WEIGHTED}, {q.prefs()} SELECT id, pref FROM pf")
def preferred_neighbor(spark: SparkSession, d: str) -> DataFrame:
    return mt.preferences(weighted(spark, d)[1])


@query("preferred_neighbor_bounded", f"WITH {WEIGHTED}, {q.prefs(where='cu + cv <= 60')} SELECT id, pref FROM pf")
def preferred_neighbor_bounded(spark: SparkSession, d: str) -> DataFrame:
    return mt.preferences(weighted(spark, d)[1], 60)


@query("mutual_match", f"WITH {ONE_ROUND} SELECT id, coarse_id FROM mt")
def mutual_match(spark: SparkSession, d: str) -> DataFrame:
    return one_round(spark, d)[1]


OPEN = "src NOT IN (SELECT id FROM mt) AND dst NOT IN (SELECT id FROM mt)"


@query("match_two_rounds", f"WITH {q.graph('copurchase')}, {q.RATED}, {q.prefs()}, {q.mutual()}, {q.prefs('p2', OPEN)}, {q.mutual('p2', 'm2')} SELECT id, coarse_id FROM mt UNION ALL SELECT id, coarse_id FROM m2")
def match_two_rounds(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    rating = mt.rated(g.edges, g.vertices)
    first = mt.mutual_pairs(mt.preferences(rating))
    return first.unionByName(mt.mutual_pairs(mt.preferences(rating, matched=first)))


@query("unmatched_vertices", f"WITH {ONE_ROUND} SELECT id FROM v WHERE id NOT IN (SELECT id FROM mt)")
def unmatched_vertices(spark: SparkSession, d: str) -> DataFrame:
    g, matched = one_round(spark, d)
    return mt.unmatched(g.vertices, matched).select("id")


NONE_MATCHED = "id long, coarse_id long"
LEAVES = "SELECT src AS id, max(dst) AS hub FROM e GROUP BY src HAVING count(*) = 1"


@query("leaf_match", f"WITH {q.graph('chain')}, {q.paired(LEAVES, 'hub')} SELECT id, coarse_id FROM pr")
def leaf_match(spark: SparkSession, d: str) -> DataFrame:
    return mt.match_leaves(src.chains(spark, d), spark.createDataFrame([], NONE_MATCHED))


TWINS = "SELECT src AS id, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS near FROM e GROUP BY src"


@query("twin_match", f"WITH {q.graph('trade')}, {q.paired(TWINS, 'near')} SELECT id, coarse_id FROM pr")
def twin_match(spark: SparkSession, d: str) -> DataFrame:
    return mt.match_twins(src.trade(spark, d), spark.createDataFrame([], NONE_MATCHED))


@query("relative_match", f"WITH {q.graph('copurchase')}, {q.RATED}, {q.prefs()}, {q.paired('SELECT id, pref FROM pf', 'pref')} SELECT id, coarse_id FROM pr")
def relative_match(spark: SparkSession, d: str) -> DataFrame:
    return mt.match_relatives(src.copurchase(spark, d), spark.createDataFrame([], NONE_MATCHED))


CONTRACTED = f"{ONE_ROUND}, {q.COARSE}"
COARSE_EDGES = "SELECT s.coarse_id AS src, t.coarse_id AS dst, CAST(sum(e.w) AS BIGINT) AS w FROM e JOIN pj s ON s.id = e.src JOIN pj t ON t.id = e.dst WHERE s.coarse_id <> t.coarse_id GROUP BY s.coarse_id, t.coarse_id"


def contracted(spark: SparkSession, d: str) -> tuple[TaskGraph, DataFrame]:
    g, matched = one_round(spark, d)
    return g, ct.completed(g.vertices, matched)


@query("coarse_degree_bound", f"WITH {CONTRACTED} SELECT coarse_id, CAST(sum(deg) AS BIGINT) AS bound FROM (SELECT pj.coarse_id, (SELECT count(*) FROM e WHERE e.src = pj.id) AS deg FROM pj) GROUP BY coarse_id")
def coarse_degree_bound(spark: SparkSession, d: str) -> DataFrame:
    return ct.coarse_degree_bound(*contracted(spark, d))


@query("contract_graph", f"WITH {CONTRACTED} {COARSE_EDGES}")
def contract_graph(spark: SparkSession, d: str) -> DataFrame:
    return ct.contract(*contracted(spark, d)).edges


@query("contract_weights", f"WITH {CONTRACTED} SELECT coarse_id AS id, CAST(sum(c) AS BIGINT) AS c FROM v JOIN pj ON pj.id = v.id GROUP BY coarse_id")
def contract_weights(spark: SparkSession, d: str) -> DataFrame:
    return ct.contract(*contracted(spark, d)).vertices


@query("project_mapping", f"WITH {CONTRACTED} SELECT id, CAST(coarse_id % 32 AS INTEGER) AS pe FROM pj")
def project_mapping(spark: SparkSession, d: str) -> DataFrame:
    g, projection = contracted(spark, d)
    coarse = src.trivial_mapping(ct.coarse_vertices(g.vertices, projection), 32)
    return ct.uncontract(coarse, projection)


# moves, on the mesh with unit weights from the modulo mapping

START = f"{q.graph('mesh')}, {q.mapping()}, {q.conn()}"
PROPOSED = f"{START}, {q.gain(T32)}, {q.best()}, prop AS (SELECT * FROM best WHERE gain >= 0)"
ROUND = f"{PROPOSED}, {q.regain(T32)}, mv AS (SELECT id, pe_old, pe_new, gain FROM re WHERE regain >= 0), {q.moved('m', 'mv', 'm2')}"


def start(spark: SparkSession, d: str) -> tuple[TaskGraph, DataFrame, DataFrame]:
    g = src.mesh(spark, d)
    m = mod(g)
    return g, m, ob.connectivity(g.edges, m)


def first_round(spark: SparkSession, d: str) -> tuple[TaskGraph, DataFrame, DataFrame, DataFrame]:
    g, m, conn = start(spark, d)
    return g, m, conn, barrier(lp.label_propagation(g.edges, conn, m, T32))  # a round ends in a barrier


@query("connectivity", f"WITH {START} SELECT id, pe, w FROM conn")
def connectivity(spark: SparkSession, d: str) -> DataFrame:
    return start(spark, d)[2]


@query("connectivity_map", f"WITH {START} SELECT id, string_agg(pe || ':' || w, ',' ORDER BY pe) AS blocks FROM conn GROUP BY id")
def connectivity_map(spark: SparkSession, d: str) -> DataFrame:
    packed = ob.connectivity_map(start(spark, d)[2])
    shown = F.transform(F.map_entries("blocks"), lambda x: F.concat_ws(":", x["key"].cast("string"), x["value"].cast("string")))
    return packed.select("id", F.array_join(shown, ",").alias("blocks"))


@query("gain_table", f"WITH {START}, {q.gain(T32)} SELECT id, pe_new, gain FROM gain")
def gain_table(spark: SparkSession, d: str) -> DataFrame:
    _, m, conn = start(spark, d)
    return ob.gains(conn, m, T32).select("id", "pe_new", "gain")


@query("gain_table_matrix", f"WITH {START}, {q.gain(T32)} SELECT id, pe_new, gain FROM gain")
def gain_table_matrix(spark: SparkSession, d: str) -> DataFrame:
    _, m, conn = start(spark, d)
    return ob.gains(conn, m, MatrixTopology.of(T32.matrix(spark))).select("id", "pe_new", "gain")


CUT_GAIN = "SELECT c.id, c.pe AS pe_new, CAST(c.w - coalesce(o.w, 0) AS BIGINT) AS gain FROM conn c JOIN m ON m.id = c.id LEFT JOIN conn o ON o.id = c.id AND o.pe = m.pe WHERE c.pe <> m.pe"


@query("cut_gain_table", f"WITH {START} {CUT_GAIN}")
def cut_gain_table(spark: SparkSession, d: str) -> DataFrame:
    _, m, conn = start(spark, d)
    return ob.cut_gains(conn, m).select("id", "pe_new", "gain")


@query("propose_moves", f"WITH {PROPOSED} SELECT id, pe_old, pe_new, gain FROM prop")
def propose_moves(spark: SparkSession, d: str) -> DataFrame:
    _, m, conn = start(spark, d)
    return lp.propose(conn, m, T32)


RELAXED = "SELECT best.id, best.pe_old, best.pe_new, best.gain FROM best LEFT JOIN conn o ON o.id = best.id AND o.pe = best.pe_old WHERE best.gain >= 0 OR -best.gain < floor(0.5 * coalesce(o.w, 0))"


@query("relaxed_filter", f"WITH {q.graph('copurchase')}, {q.mapping('mod', 8)}, {q.conn()}, {q.gain(Topology.flat(8))}, {q.best()} {RELAXED}")
def relaxed_filter(spark: SparkSession, d: str) -> DataFrame:
    g = src.copurchase(spark, d)
    m = mod(g, 8)
    return lp.propose(ob.connectivity(g.edges, m), m, Topology.flat(8), filter_mode="relaxed", relaxed_c=0.5)


@query("reevaluated_moves", f"WITH {ROUND} SELECT id, pe_old, pe_new, gain, regain FROM re WHERE regain >= 0")
def reevaluated_moves(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn = start(spark, d)
    return lp.reevaluated(g.edges, lp.propose(conn, m, T32), m, T32).filter("regain >= 0")


SECOND = f"{ROUND}, {q.conn('m2', 'conn2')}, {q.gain(T32, 'm2', 'conn2', 'gain2')}, {q.best('gain2', 'best2')}"


@query("locked_second_round", f"WITH {SECOND} SELECT id, pe_old, pe_new, gain FROM best2 WHERE gain >= 0 AND id NOT IN (SELECT id FROM mv)")
def locked_second_round(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, moves = first_round(spark, d)
    after = lp.apply_moves(m, moves)
    return lp.propose(ob.connectivity(g.edges, after), after, T32, locked=moves)


@query("apply_moves", f"WITH {ROUND} SELECT id, CAST(pe AS INTEGER) AS pe FROM m2")
def apply_moves(spark: SparkSession, d: str) -> DataFrame:
    _, m, _, moves = first_round(spark, d)
    return lp.apply_moves(m, moves)


AFTER = f"WITH {ROUND}, {q.conn('m2', 'conn2')} SELECT id, pe, w FROM conn2"


@query("connectivity_delta", AFTER)
def connectivity_delta(spark: SparkSession, d: str) -> DataFrame:
    g, _, conn, moves = first_round(spark, d)
    return lp.update_connectivity(conn, g.edges, moves)


@query("connectivity_rebuild", AFTER)
def connectivity_rebuild(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, moves = first_round(spark, d)
    return lp.rebuild_connectivity(conn, g.edges, lp.apply_moves(m, moves), moves)


@query("cached_proposals", f"WITH {SECOND} SELECT id, pe_old, pe_new, gain FROM best2")
def cached_proposals(spark: SparkSession, d: str) -> DataFrame:
    # the graph, its connectivity and the vertices to do anew are read many times, so they are stored
    g, m, _ = start(spark, d)
    edges = barrier(g.edges)
    conn = barrier(ob.connectivity(edges, m))
    moves = barrier(lp.label_propagation(edges, conn, m, T32))
    before = lp.best_moves(ob.gains(conn, m, T32))
    after = lp.apply_moves(m, moves)
    return lp.refreshed(before, barrier(lp.dirty(edges, moves)), lp.update_connectivity(conn, edges, moves), after, T32)


@query("moved_except", f"WITH {ROUND} SELECT id, CAST(pe AS INTEGER) AS pe FROM m2 EXCEPT SELECT id, pe FROM m")
def moved_except(spark: SparkSession, d: str) -> DataFrame:
    _, m, _, moves = first_round(spark, d)
    return lp.apply_moves(m, moves).exceptAll(m)


# rebalancing, on the mesh with part sizes as weights from the modulo mapping

HEAVY = f"{q.graph('mesh', 'size')}, {q.mapping()}, {q.conn()}, {q.blocks(32)}, {q.CANDIDATES}"
WEAK = f"{HEAVY}, {q.targets(T32)}, {q.PREFIX}"
REBALANCED = "SELECT id, pe_old, CAST(pe_new AS INTEGER) AS pe_new, gain, bucket, before FROM px"


def heavy(spark: SparkSession, d: str):
    g = src.mesh(spark, d, "size")
    m = mod(g)
    blocks = rb.block_table(g.vertices, m, limits(spark, 32, total(g), CONFIG))
    return g, m, ob.connectivity(g.edges, m), blocks


@query("rebalance_candidates", f"WITH {HEAVY} SELECT id, c, pe_old, weight, bound FROM cand")
def rebalance_candidates(spark: SparkSession, d: str) -> DataFrame:
    g, m, _, blocks = heavy(spark, d)
    return rb.candidates(g.vertices, m, blocks, CONFIG).select("id", "c", "pe_old", "weight", "bound")


@query("rebalance_targets", f"WITH {HEAVY}, {q.targets(T32)} SELECT id, pe_old, CAST(pe_new AS INTEGER) AS pe_new, gain FROM tg")
def rebalance_targets(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, blocks = heavy(spark, d)
    movers = rb.candidates(g.vertices, m, blocks, CONFIG)
    return rb.targets(movers, conn, m, blocks, T32, CONFIG).select("id", "pe_old", "pe_new", "gain")


@query("loss_buckets", f"WITH {HEAVY}, {q.targets(T32)} SELECT {q.BUCKET} AS bucket, count(*) AS n FROM tg GROUP BY 1")
def loss_buckets(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, blocks = heavy(spark, d)
    movers = rb.targets(rb.candidates(g.vertices, m, blocks, CONFIG), conn, m, blocks, T32, CONFIG)
    return movers.groupBy(rb.loss_bucket(F.col("gain")).alias("bucket")).agg(F.count("*").alias("n"))


@query("weak_rebalance_moves", f"WITH {WEAK} {REBALANCED}")
def weak_rebalance_moves(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, blocks = heavy(spark, d)
    return rb.weak(g.vertices, conn, m, blocks, T32, CONFIG)


@query("weak_rebalance_moves_comm", f"WITH {HEAVY}, {q.targets(T32, 'comm')}, {q.PREFIX} {REBALANCED}")
def weak_rebalance_moves_comm(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, blocks = heavy(spark, d)
    return rb.weak(g.vertices, conn, m, blocks, T32, CONFIG.but(rebalance_objective="comm"))


LINE = "ln AS (SELECT *, CAST(coalesce(sum(c) OVER (ORDER BY bucket, id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM px), rm AS (SELECT pe AS pe_to, bound - weight AS room, sum(bound - weight) OVER (ORDER BY pe) AS high FROM b WHERE weight < bound)"


@query("strong_rebalance_moves", f"WITH {HEAVY}, {q.targets(T32, limit='bound - 1')}, {q.PREFIX}, {LINE} SELECT id, pe_old, CAST(pe_to AS INTEGER) AS pe_new, gain, bucket, start AS before FROM ln JOIN rm ON start >= high - room AND start + c <= high")
def strong_rebalance_moves(spark: SparkSession, d: str) -> DataFrame:
    g, m, conn, blocks = heavy(spark, d)
    return rb.strong(g.vertices, conn, m, blocks, T32, CONFIG)


# multisection's bounds

PARTS = "pt AS (SELECT m.pe AS part, CAST(sum(v.c) AS BIGINT) AS pw FROM v JOIN m ON m.id = v.id GROUP BY m.pe)"
EPS = "round(greatest(0.0, pow((1 + 0.03) * 32 * (SELECT sum(c) FROM v) / (192 * pw), 1.0 / 2) - 1), 6)"


@query("adaptive_imbalance", f"WITH {q.parts('size')}, {q.mapping('range', 6)}, {PARTS} SELECT part, 2 AS levels_left, CAST({EPS} AS DOUBLE) AS eps FROM pt")
def adaptive_imbalance(spark: SparkSession, d: str) -> DataFrame:
    v = src.parts(spark, d, "size")
    part = src.trivial_mapping(v, 6, "range").withColumnRenamed("pe", "part")
    sums = v.agg(F.sum("c")).head()[0]
    own = ms.part_bounds(v, part, sums, 192, 4, 8, 2, CONFIG)
    return own.select("part", "levels_left", F.round("eps", 6).alias("eps"))


__all__ = ["QUERIES", "SQL", "floor_div"]
