"""Task graphs from streams of events(event_id, ts, user_id, ...): users that act together communicate.

Every function works on a batch DataFrame too, which is how the streams are tested. State is bounded by watermarks.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from taskmap import objective as measures
from taskmap.graph import symmetrized
from taskmap.operators import moves as lp
from taskmap.topology import Topology

LATE = "30 minutes"
EVENT = "event_id long, ts timestamp, user_id long"
#: Users of a window in one block; a row makes at most the square of it at once.
BLOCK = 256


def on_time(events: DataFrame, late: str = LATE) -> DataFrame:
    """A watermark on streams, whose event time must be a timestamp with time zone; batches stay as they are."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if events.isStreaming else events


def window_activity(events: DataFrame, width: str = "10 minutes", slide: str | None = None, late: str = LATE) -> DataFrame:
    """start, user_id, n: events of a user in tumbling (or, with slide, sliding) windows."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    return on_time(events, late).groupBy(span.alias("span"), "user_id").agg(F.count("*").alias("n")).select(F.col("span.start").alias("start"), "user_id", "n")


def window_edges(events: DataFrame, width: str = "10 minutes", slide: str | None = None, late: str = LATE) -> DataFrame:
    """start, a, b, w: users with events in one window; w is the product of their numbers of events.

    All pairs of a window, whatever its size. Its users are gathered in sorted order and cut into blocks; a pair of blocks
    is a row of its own and dealt out before it becomes pairs of users, so a hot window is spread over all tasks.
    """
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    own = on_time(events, late).filter("user_id IS NOT NULL").groupBy(span.alias("span"), F.col("user_id").alias("id")).agg(F.count("*").alias("n"))
    users = own.groupBy("span").agg(F.array_sort(F.collect_list(F.struct("id", "n"))).alias("r")).select(F.col("span.start").alias("start"), "r")
    first = users.select("start", "r", F.explode(F.expr(f"sequence(0, size(r) - 1, {BLOCK})")).alias("i"))
    both = first.select("start", "r", "i", F.explode(F.expr(f"sequence(i, size(r) - 1, {BLOCK})")).alias("j"))
    blocks = both.select("start", "i", "j", F.expr(f"slice(r, i + 1, {BLOCK})").alias("x"), F.expr(f"slice(r, j + 1, {BLOCK})").alias("y"))
    pairs = F.expr("flatten(transform(x, p -> transform(filter(y, q -> q.id > p.id), q -> struct(p.id as a, q.id as b, p.n * q.n as w))))")
    tasks = int(events.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # by number, as few bytes of blocks make many pairs
    return blocks.repartition(tasks, "start", "i", "j").select("start", F.explode(pairs).alias("p")).select("start", "p.a", "p.b", "p.w")


def session_counts(events: DataFrame, gap: str = "15 minutes", late: str = LATE) -> DataFrame:
    """user_id, start, n: a user's events without a gap of that length."""
    own = on_time(events, late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return own.select("user_id", F.col("s.start").alias("start"), "n")


def distinct_events(events: DataFrame, late: str = LATE) -> DataFrame:
    """Each event once, as far as repeats arrive within the watermark."""
    if events.isStreaming:
        return on_time(events, late).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def handoffs(events: DataFrame, lane: str) -> DataFrame:
    """lane, a, b: users of consecutive events within each value of column lane, by a state of one user per lane."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        users = rows["user_id"].tolist()
        before = [last, *users[:-1]]
        state.update((int(users[-1]),))
        out = [(key[0], int(a), int(b)) for a, b in zip(before, users) if a is not None and a != b]
        yield pd.DataFrame(out, columns=["lane", "a", "b"]).astype({"a": "int64", "b": "int64"})

    rows = events.select(F.col(lane).cast("string").alias("lane"), "event_id", "ts", "user_id")
    return rows.groupBy("lane").applyInPandasWithState(step, "lane string, a long, b long", "last long", "append", GroupStateTimeout.NoTimeout)


def late_share(events: DataFrame, kept: DataFrame) -> DataFrame:
    """n_events, n_kept, n_late of a finished stream against the batch of all events."""
    return events.agg(F.count("*").alias("n_events")).join(kept.agg(F.sum("n").alias("n_kept"))).withColumn("n_late", F.col("n_events") - F.col("n_kept"))


def live_objective(edges: DataFrame, mapping: DataFrame, topology: Topology) -> DataFrame:
    """start, x: what a fixed mapping pays for each of a window's edges, to be summed; the mapping is the static side of the joins."""
    s = mapping.select(F.col("id").alias("a"), F.col("pe").alias("pe_a"))
    t = mapping.select(F.col("id").alias("b"), F.col("pe").alias("pe_b"))
    own = edges.join(s, "a").join(t, "b")
    return own.select("start", (F.lit(2) * F.col("w") * topology.distance("pe_a", "pe_b")).alias("x"))


class Repair:
    """Keeps a mapping up with a stream: each micro-batch's edges join the graph, and a few rounds of moves follow."""

    def __init__(self, edges: DataFrame, mapping: DataFrame, topology: Topology, rounds: int = 2):
        self.edges, self.mapping, self.topology, self.rounds = edges, mapping, topology, rounds

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from taskmap.plans.iterate import barrier

        new = symmetrized(batch.select("a", "b", "w"))
        self.edges = barrier(self.edges.unionByName(new).groupBy("src", "dst").agg(F.sum("w").alias("w")))
        known = self.mapping.select("id")
        fresh = new.select(F.col("src").alias("id")).distinct().join(known, "id", "left_anti")
        self.mapping = barrier(self.mapping.unionByName(fresh.select("id", (F.col("id") % self.topology.k).cast("int").alias("pe"))))
        touched = new.select(F.col("src").alias("id")).distinct()
        locked = None
        for _ in range(self.rounds):
            # only what touches the new edges is looked at, not the whole graph
            some = self.edges.join(touched.withColumnRenamed("id", "src"), "src", "left_semi")
            conn = measures.connectivity(some, self.mapping)
            moves = barrier(lp.label_propagation(some, conn, self.mapping.join(touched, "id", "left_semi").unionByName(self.mapping.join(touched, "id", "left_anti")), self.topology, locked))
            if not moves.limit(1).count():
                break
            self.mapping = barrier(lp.apply_moves(self.mapping, moves))
            locked = moves
