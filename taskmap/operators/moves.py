"""Unconstrained label propagation: proposals, their re-evaluation, and applying moves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.graph import keyed
from taskmap.objective import costs, gains
from taskmap.topology import MatrixTopology, Topology, with_distance


def best_moves(gain: DataFrame) -> DataFrame:
    """id, pe_old, pe_new, gain: the best neighbouring block of each vertex, the lowest PE among equals."""
    top = F.max_by(F.struct("pe_old", "pe_new", "gain"), F.struct("gain", -F.col("pe_new"))).alias("m")
    return gain.groupBy("id").agg(top).select("id", "m.*")


def propose(conn: DataFrame, mapping: DataFrame, topology: Topology | MatrixTopology, locked: DataFrame | None = None, filter_mode: str = "nonnegative", relaxed_c: float = 0.25, best: DataFrame | None = None) -> DataFrame:
    """Best moves that pass the first filter; locked vertices propose nothing. Where they are known, best moves are given.

    "nonnegative" keeps gains of at least 0; "relaxed" also losses below the floor of c times the volume into the own block.
    """
    moves = best_moves(gains(conn, mapping, topology)) if best is None else best
    if locked is not None:
        moves = moves.join(keyed(locked.select("id")), "id", "left_anti")
    if filter_mode == "nonnegative":
        return moves.filter("gain >= 0")
    own = conn.select("id", F.col("pe").alias("pe_old"), F.col("w").alias("inside"))
    allowed = F.floor(F.lit(relaxed_c) * F.coalesce("inside", F.lit(0)))
    return moves.join(keyed(own), ["id", "pe_old"], "left").filter((F.col("gain") >= 0) | (-F.col("gain") < allowed)).select("id", "pe_old", "pe_new", "gain")


def reevaluated(edges: DataFrame, proposals: DataFrame, mapping: DataFrame, topology: Topology | MatrixTopology) -> DataFrame:
    """id, pe_old, pe_new, gain, regain: the gain if all proposals before it (larger gain, then smaller id) are carried out.

    The order is a comparison of two columns, not a sort; only edges of proposers are touched.
    """
    own = proposals.select(F.col("id").alias("src"), "pe_old", "pe_new", "gain")
    others = proposals.select(F.col("id").alias("dst"), F.col("pe_new").alias("moved_to"), F.col("gain").alias("their_gain"))
    at = mapping.select(F.col("id").alias("dst"), F.col("pe").alias("stays_at"))
    near = edges.join(keyed(own), "src").join(keyed(at), "dst").join(keyed(others), "dst", "left")
    earlier = (F.col("their_gain") > F.col("gain")) | ((F.col("their_gain") == F.col("gain")) & (F.col("dst") < F.col("src")))
    near = near.withColumn("at", F.when(earlier, F.col("moved_to")).otherwise(F.col("stays_at")))
    near = with_distance(with_distance(near, topology, "pe_old", "at", "d_old"), topology, "pe_new", "at", "d_new")
    change = F.sum(F.col("w") * (F.col("d_old") - F.col("d_new"))).alias("regain")
    return near.groupBy(F.col("src").alias("id"), "pe_old", "pe_new", "gain").agg(change)


def label_propagation(edges: DataFrame, conn: DataFrame, mapping: DataFrame, topology: Topology | MatrixTopology, locked: DataFrame | None = None, filter_mode: str = "nonnegative", relaxed_c: float = 0.25, best: DataFrame | None = None) -> DataFrame:
    """id, pe_old, pe_new, gain of the moves of a round."""
    proposals = propose(conn, mapping, topology, locked, filter_mode, relaxed_c, best)
    return reevaluated(edges, proposals, mapping, topology).filter("regain >= 0").select("id", "pe_old", "pe_new", "gain")


def apply_moves(mapping: DataFrame, moves: DataFrame) -> DataFrame:
    new = moves.select("id", F.col("pe_new").alias("new"))
    return mapping.join(keyed(new), "id", "left").select("id", F.coalesce("new", "pe").alias("pe"))


def connectivity_change(edges: DataFrame, moves: DataFrame) -> DataFrame:
    """id, pe, w: what neighbours of movers lose at the old block and win at the new one.

    Edges are symmetric, so the movers' own rows tell their neighbours; only those are read.
    """
    m = moves.select(F.col("id").alias("src"), "pe_old", "pe_new")
    near = edges.join(keyed(m), "src")
    sides = F.array(F.struct(F.col("pe_old").alias("pe"), (-F.col("w")).alias("w")), F.struct(F.col("pe_new").alias("pe"), F.col("w").alias("w")))
    return near.select(F.col("dst").alias("id"), F.explode(sides).alias("x")).groupBy("id", "x.pe").agg(F.sum("x.w").alias("w")).filter("w <> 0")


def update_connectivity(conn: DataFrame, edges: DataFrame, moves: DataFrame) -> DataFrame:
    """The connectivity after moves: their change is added to it."""
    return conn.unionByName(connectivity_change(edges, moves)).groupBy("id", "pe").agg(F.sum("w").alias("w")).filter("w <> 0")


def rebuild_connectivity(conn: DataFrame, edges: DataFrame, mapping: DataFrame, moves: DataFrame) -> DataFrame:
    """The same by dropping the affected vertices' rows and filling them anew from the mapping after the moves."""
    touched = edges.join(keyed(moves.select(F.col("id").alias("src"))), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
    after = mapping.select(F.col("id").alias("dst"), "pe")
    own = edges.join(keyed(touched.select(F.col("id").alias("src"))), "src", "left_semi").join(keyed(after), "dst")
    return conn.join(keyed(touched), "id", "left_anti").unionByName(own.groupBy(F.col("src").alias("id"), "pe").agg(F.sum("w").alias("w")))


def dirty(edges: DataFrame, moves: DataFrame) -> DataFrame:
    """Vertices whose best move may have changed: movers and their neighbours."""
    near = edges.join(keyed(moves.select(F.col("id").alias("src"))), "src", "left_semi").select(F.col("dst").alias("id"))
    return near.unionByName(moves.select("id")).distinct()


def refreshed(cached: DataFrame, changed: DataFrame, conn: DataFrame, mapping: DataFrame, topology: Topology | MatrixTopology) -> DataFrame:
    """Best moves of all vertices, computed anew only for the changed ones."""
    some = conn.join(keyed(changed), "id", "left_semi")
    new = best_moves(gains(some, mapping.join(keyed(changed), "id", "left_semi"), topology))
    return cached.join(keyed(changed), "id", "left_anti").unionByName(new)


__all__ = ["apply_moves", "best_moves", "connectivity_change", "costs", "dirty", "label_propagation", "propose", "rebuild_connectivity", "reevaluated", "refreshed", "update_connectivity"]
