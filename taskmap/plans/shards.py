"""Rounds over shards: a graph in a few arrays, one step of all of them in one job.

A shard is a range of ids with the edges that begin there, about FULL of them, so a task's memory has a bound whatever the
graph's size. Shards are packed once and kept; what changes goes from step to step as a table with the state of each shard and
its letters to the shards it shares edges with, which hold one value for each vertex at the border, in the order of ids, and no
ids. The driver gets numbers of blocks. Ranges are in the order of ids, so sums over shards order rows as sorting them would.
"""

from __future__ import annotations

import os
import pickle
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import BarrierTaskContext, StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from taskmap.functions.kernels import _best_by
from taskmap.graph import TaskGraph, keyed
from taskmap.operators.noise import edge_noise_array
from taskmap.plans.iterate import barrier, release, steady

#: Directed edges of a shard, about, and how many are worth one where there are fewer.
FULL, WORTH = 400_000, 50_000
#: A vertex's edges are in one shard; a graph with more edges at a vertex than this keeps to plans over rows.
HUB = 4_000_000

TABLE = "shard int, sender int, body binary"
SCHEMA = pa.schema([("shard", pa.int32()), ("sender", pa.int32()), ("body", pa.binary())])

#: Values at the borders up to which all steps are one job, whose tasks run side by side and read all letters.
BORDER = 2_000_000

#: run(shard's arrays, its number, its state, letters by sender) -> new state, letters by receiver, what the driver is told.
Run = Callable[[dict, int, dict, dict], tuple[dict, dict, dict]]


def _table(rows: list[tuple[int, int, dict]]) -> pa.Table:
    columns = list(zip(*rows))
    return pa.table([pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int32()), pa.array([pickle.dumps(x, 5) for x in columns[2]], pa.binary())], schema=SCHEMA)


def _number(id: Column, cuts: list[int]) -> Column:
    if not cuts:
        return F.lit(0)
    return F.size(F.filter(F.array(*[F.lit(x) for x in cuts]), lambda x: x <= id))


def letters(g: dict, **values: np.ndarray) -> dict[int, dict]:
    """The values of the border, for each shard that shares it."""
    return {t: {name: x[at] for name, x in values.items()} for t, at in g["send"].items()}


def halo(g: dict, mail: dict, name: str, own: np.ndarray) -> np.ndarray:
    """The own values, then those of the vertices beyond the border."""
    out = np.zeros(len(g["halo"]), own.dtype)
    for t, letter in mail.items():
        out[g["owner"] == t] = letter[name]
    return np.concatenate((own, out))


def _pack(table: pa.Table, s: int, cuts: np.ndarray, start: str) -> pa.Table:
    is_vertex = table.column("dst").is_null()
    v, e = table.filter(is_vertex), table.filter(table.column("dst").is_valid())
    col = lambda t, c: t.column(c).to_numpy()
    order = np.argsort(col(v, "id"))
    ids, c, value = (col(v, x)[order] for x in ("id", "c", "value"))
    src, dst, w = col(e, "id"), col(e, "dst"), col(e, "w").astype(np.int64)
    src = np.searchsorted(ids, src)
    by = np.lexsort((dst, src))
    src, dst, w = src[by].astype(np.int32), dst[by], w[by]
    at = np.minimum(np.searchsorted(ids, dst), max(0, len(ids) - 1))
    inside = ids[at] == dst if len(ids) else np.zeros(0, bool)
    beyond = np.unique(dst[~inside])
    local = np.where(inside, at, len(ids) + np.searchsorted(beyond, dst)).astype(np.int32)
    owner = np.searchsorted(cuts, beyond, side="right").astype(np.int32)
    of = np.searchsorted(cuts, dst, side="right")
    send = {int(t): np.unique(src[~inside & (of == t)]) for t in np.unique(owner)}
    g = {"ids": ids.astype(np.int64), "c": c.astype(np.int64), "src": src, "dst": local, "w": w, "halo": beyond.astype(np.int64), "owner": owner, "send": send}
    first = {start: value.astype(np.int64)}
    border = {"border": sum(map(len, send.values()))}
    return _table([(s, -1, g), (s, s, first), *((t, s, x) for t, x in letters(g, **first).items()), (-1, s, border)])


class Ring:
    """The shards of a task, and the same steps as those of Shards, within one job whose tasks run side by side.

    Letters are files in the folder for checkpoints, which all executors share; an attempt has a folder of its own. (Spark's
    own exchange between such tasks waits for a second each time.)
    """

    def __init__(self, batches: Iterator[pa.RecordBatch], folder: str, tasks: int) -> None:
        context = BarrierTaskContext.get()
        attempt = context.allGather(uuid.uuid4().hex)[0]
        self.folder, self.tasks, self.me, self.number = f"{folder}/{attempt}", tasks, context.partitionId(), 0
        os.makedirs(self.folder, exist_ok=True)
        self.graphs: dict[int, dict] = {}
        own, mail = {}, {}
        for batch in batches:
            for s, a, body in zip(*(batch.column(x).to_pylist() for x in ("shard", "sender", "body"))):
                at = self.graphs if a < 0 else own if a == s else mail.setdefault(s, {})
                at[s if a < 0 or a == s else a] = pickle.loads(body)
        self.first = {s: (own[s], mail.get(s, {})) for s in self.graphs}

    def step(self, state: dict, run: Run) -> tuple[dict, list[dict]]:
        new, sent = {}, []
        for s, (own, mail) in state.items():
            new[s], out, told = run(self.graphs[s], s, own, mail)
            sent.append((s, out, told))
        words = self._exchanged(pickle.dumps(sent, 5))
        every = sorted((x for word in words for x in pickle.loads(word)), key=lambda x: x[0])
        return {s: (own, {a: out[s] for a, out, _ in every if s in out}) for s, own in new.items()}, [told for _, _, told in every]

    def _exchanged(self, own: bytes) -> list[bytes]:
        """What all tasks have to say in this step. A file is renamed when it is whole; one that all have read is deleted."""
        name = f"{self.folder}/{self.number}-"
        with open(f"{name}{self.me}.part", "wb") as f:
            f.write(own)
        os.rename(f"{name}{self.me}.part", f"{name}{self.me}")
        words = []
        for i in range(self.tasks):
            while not os.path.exists(f"{name}{i}"):
                time.sleep(0.002)
            with open(f"{name}{i}", "rb") as f:
                words.append(f.read())
        if self.number:
            os.remove(f"{self.folder}/{self.number - 1}-{self.me}")
        self.number += 1
        return words

    def release(self, *states: dict) -> None:
        """Memory is freed by itself."""


class Shards:
    """A graph's shards. start(id, value) goes, under that name, into the first state and its letters."""

    def __init__(self, graph: TaskGraph, name: str, start: DataFrame) -> None:
        spark = graph.edges.sparkSession
        m = graph.edges.count()
        count = max(1, -(-m // FULL), min(spark.sparkContext.defaultParallelism, -(-m // WORTH)))
        ids = graph.vertices.select("id").unionByName(graph.edges.select(F.col("src").alias("id")))
        with steady(spark):
            told = ids.agg(F.percentile_approx("id", [i / count for i in range(1, count)], 10_000).alias("x")).head()["x"] if count > 1 else []
        cuts = sorted(set(told or []))
        none = F.lit(None).cast("long")
        v = graph.vertices.join(keyed(start), "id").select("id", "c", F.col("value").cast("long").alias("value"), none.alias("dst"), none.alias("w"))
        e = graph.edges.select(F.col("src").alias("id"), none.alias("c"), none.alias("value"), "dst", "w")
        rows = v.unionByName(e).withColumn("shard", _number(F.col("id"), cuts))
        limits = np.array(cuts, np.int64)
        self.count = len(cuts) + 1
        packed = rows.groupBy("shard").applyInArrow(lambda key, table: _pack(table, key[0].as_py(), limits, name), TABLE)
        self.packed = barrier(packed)
        self.border = sum(pickle.loads(x["body"])["border"] for x in self.packed.filter("shard = -1").collect())
        self.first = self.packed.filter("sender >= 0 and shard >= 0")
        self._graphs: DataFrame | None = None

    @property
    def graphs(self) -> DataFrame:
        if self._graphs is None:
            self._graphs = self.packed.filter("sender = -1").repartition(self.count, "shard").persist(StorageLevel.MEMORY_AND_DISK)
            self._graphs.count()
        return self._graphs

    def release(self, *states: DataFrame) -> None:
        release(*states)

    def together(self, loop: Callable[[Shards | Ring], dict | DataFrame], run: Callable[[dict, dict], tuple[np.ndarray, np.ndarray]], name: str, kind: str) -> DataFrame:
        """id and a column by that name, as rows() of the state that loop ends with. Where the borders are short and the
        folder for checkpoints is one of plain files, all steps are one job."""
        spark = self.packed.sparkSession
        shared = spark._jvm.org.apache.hadoop.fs.Path(spark.sparkContext._jsc.sc().getCheckpointDir().get()).toUri()
        if shared.getScheme() not in (None, "file") or self.border > BORDER or spark.conf.get("spark.dynamicAllocation.enabled", "false") == "true":
            last = loop(self)
            out = self.rows(last, run, name, kind)
            release(last)
            return out
        tasks = min(self.count, spark.sparkContext.defaultParallelism)
        # for each task a key that is dealt to it, so that shards are spread evenly
        dealt = {r["task"]: r["key"] for r in spark.range(64 * tasks).select(F.col("id").cast("int").alias("key")).select("key", F.pmod(F.hash("key"), F.lit(tasks)).alias("task")).collect()}
        slots = F.array(*[F.lit(dealt[i]) for i in range(tasks)])
        types = {"int": pa.int32(), "long": pa.int64()}
        folder = f"{shared.getPath()}/letters-{uuid.uuid4().hex}"

        def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ring = Ring(batches, folder, tasks)
            for s, (own, _) in loop(ring).items():
                ids, x = run(ring.graphs[s], own)
                yield pa.record_batch([pa.array(ids, pa.int64()), pa.array(x, types[kind])], ["id", name])

        rows = self.packed.filter("shard >= 0").withColumn("slot", F.element_at(slots, (F.col("shard") % tasks + 1).cast("int")))
        out = barrier(rows.repartition(tasks, "slot").mapInArrow(task, f"id long, {name} {kind}", barrier=True))
        path = spark._jvm.org.apache.hadoop.fs.Path(f"file://{folder}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
        return out

    def step(self, state: DataFrame, run: Run) -> tuple[DataFrame, list[dict]]:
        """The next state, and what each shard tells the driver, in the order of shards."""

        def task(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
            s = key[0].as_py()
            if not left.num_rows:
                return SCHEMA.empty_table()
            g = pickle.loads(left.column("body")[0].as_py())
            mail = {a: pickle.loads(b) for a, b in zip(right.column("sender").to_pylist(), right.column("body").to_pylist())}
            new, out, told = run(g, s, mail.pop(s), mail)
            return _table([(s, s, new), *((t, s, x) for t, x in out.items()), (-1, s, told)])

        held = barrier(self.graphs.groupBy("shard").cogroup(state.groupBy("shard")).applyInArrow(task, TABLE))
        told = sorted(held.filter("shard = -1").select("sender", "body").collect())
        after = held.filter("shard >= 0")
        after.stored_at = held.stored_at
        return after, [pickle.loads(x["body"]) for x in told]

    def rows(self, state: DataFrame, run: Callable[[dict, dict], tuple[np.ndarray, np.ndarray]], name: str, kind: str) -> DataFrame:
        """id and a column by that name, from run(shard's arrays, its state)."""
        types = {"int": pa.int32(), "long": pa.int64()}

        def task(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
            own = right.filter(pc.equal(right.column("sender"), key[0].as_py())) if right.num_rows else right
            ids, x = run(pickle.loads(left.column("body")[0].as_py()), pickle.loads(own.column("body")[0].as_py())) if left.num_rows else ([], [])
            return pa.table([pa.array(ids, pa.int64()), pa.array(x, types[kind])], ["id", name])

        return barrier(self.graphs.groupBy("shard").cogroup(state.groupBy("shard")).applyInArrow(task, f"id long, {name} {kind}"))

    def close(self) -> None:
        if self._graphs is not None:
            self._graphs.unpersist()
        release(self.packed)


def hubs(graph: TaskGraph) -> bool:
    """Whether a vertex has more edges than a task should hold. Where all edges are few, none has."""
    if graph.edges.count() <= HUB:
        return False
    return graph.edges.groupBy("src").count().filter(F.col("count") > HUB).limit(1).count() > 0


def mutual_rounds(graph: TaskGraph, bound: int | None, rule: str, seed: int, rounds: int, enough: float) -> tuple[DataFrame, int]:
    """id, coarse_id of the vertices matched by rounds of mutual preference, and their number. Two steps a round: each open vertex
    tells whom it prefers, and pairs that prefer each other tell that they are taken."""

    def prefer(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        n, ids = len(g["ids"]), np.concatenate((g["ids"], g["halo"]))
        c = own["c_all"] if "c_all" in own else halo(g, mail, "c", own["c"])
        taken = halo(g, mail, "taken", own["taken"]) if "taken" in own else np.zeros(len(ids), bool)
        src, dst, w = g["src"], g["dst"], g["w"]
        free = ~taken[src] & ~taken[dst]
        free = np.flatnonzero(free if bound is None else free & (c[src] + c[dst] <= bound))
        u, v, x = src[free], dst[free], w[free].astype(float)
        rating = x * x / (c[u] * c[v]).astype(float) if rule == "squared_over_product" else x
        best = _best_by(u, (rating, edge_noise_array(ids[u], ids[v], seed), ids[v]))
        to = np.full(n, -1, np.int64)
        to[u[best]] = v[best]
        asks = to >= 0
        whom = np.where(asks, ids[to], 0)
        new = {"c_all": c, "taken": taken[:n], "label": own.get("label", g["ids"]), "to": to, "asks": asks, "whom": whom}
        return new, letters(g, asks=asks, whom=whom), {}

    def marry(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        ids = np.concatenate((g["ids"], g["halo"]))
        asks, whom = halo(g, mail, "asks", own["asks"]), halo(g, mail, "whom", own["whom"])
        v = np.flatnonzero(own["asks"])
        both = v[asks[own["to"][v]] & (whom[own["to"][v]] == g["ids"][v])]
        taken, label = own["taken"].copy(), own["label"].copy()
        taken[both] = True
        label[both] = np.minimum(g["ids"][both], whom[both])
        return {"c_all": own["c_all"], "taken": taken, "label": label}, letters(g, taken=taken), {"new": len(both)}

    n = graph.vertices.count()
    shards = Shards(graph, "c", graph.vertices.select("id", F.col("c").alias("value")))

    def loop(at: Shards | Ring) -> dict | DataFrame:
        state, done = at.first, 0
        for _ in range(rounds):
            asked, _ = at.step(state, prefer)
            answered, told = at.step(asked, marry)
            at.release(state, asked)
            state, new = answered, sum(x["new"] for x in told)
            done += new
            if not new or done > enough * n:
                break
        return state

    def pairs(g: dict, own: dict) -> tuple[np.ndarray, np.ndarray]:
        at = np.flatnonzero(own["taken"]) if "taken" in own else np.zeros(0, np.int64)
        return g["ids"][at], own["label"][at] if len(at) else at

    matched = shards.together(loop, pairs, "coarse_id", "long")
    shards.close()
    return matched, matched.count()
