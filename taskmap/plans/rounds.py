"""The rounds of a refinement over shards: label propagation, weak and strong rebalancing, each a few steps.

The definitions are those of taskmap.functions.kernels and of taskmap.operators: integer costs and total orders by id, so the
results are the same. The cost of a state is known with the first step of the round after it, which is run for that, too.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.config import Config
from taskmap.functions import kernels
from taskmap.functions.kernels import LOWEST, State, accepts, pass_config
from taskmap.graph import TaskGraph
from taskmap.operators.noise import edge_noise_array
from taskmap.plans.iterate import Clock
from taskmap.plans.shards import Ring, Shards, halo, letters

#: Entries of the table of volumes, vertices by blocks, that a task holds at once.
CHUNK = 2_000_000
#: Classes of loss: gains, no change, and the binary logarithm of 64 bits.
BUCKETS = 68


@dataclass(frozen=True)
class Blocks:
    """The blocks 0 to k - 1; those that are missing take no vertices and never overflow."""

    dist: np.ndarray
    part: np.ndarray
    bound: np.ndarray
    average: np.ndarray
    known: np.ndarray

    @classmethod
    def of(cls, bounds: dict[int, tuple[int, int, int]], dist: np.ndarray) -> Blocks:
        k = len(dist)
        part, bound, average, known = (np.zeros(k, t) for t in (np.int64, np.int64, np.int64, bool))
        for pe, row in bounds.items():
            part[pe], bound[pe], average[pe] = row
            known[pe] = True
        return cls(dist, part, bound, average, known)

    def excess(self, load: np.ndarray) -> int:
        return int((load - self.bound)[self.known].max()) if self.known.any() else 0


def _volumes(g: dict, at: np.ndarray, k: int) -> Iterator[tuple[int, int, np.ndarray]]:
    """Volumes of the shard's vertices into blocks, some vertices at a time."""
    n, size = len(g["ids"]), max(1, CHUNK // k)
    for a in range(0, n, size):
        b = min(n, a + size)
        e = slice(*np.searchsorted(g["src"], [a, b]))
        yield a, b, np.bincount((g["src"][e].astype(np.int64) - a) * k + at[g["dst"][e]], weights=g["w"][e], minlength=(b - a) * k).reshape(b - a, k)


def _cost(g: dict, at: np.ndarray, dist: np.ndarray) -> int:
    return int((g["w"] * dist[at[g["src"]], at[g["dst"]]]).sum())


def _loads(g: dict, pe: np.ndarray, k: int) -> np.ndarray:
    out = np.zeros(k, np.int64)
    np.add.at(out, pe, g["c"])
    return out


def _moved(g: dict, pe: np.ndarray, movers: np.ndarray, to: np.ndarray, k: int, lock: bool = False) -> tuple[dict, dict, dict]:
    pe = pe.copy()
    pe[movers] = to
    locked = np.zeros(len(pe), bool)
    locked[movers] = lock
    return {"pe": pe, "locked": locked}, letters(g, pe=pe), {"count": len(movers), "loads": _loads(g, pe, k)}


def proposing(blocks: Blocks, config: Config, locks: bool):
    """Best moves of all vertices, told to neighbours; and the cost of the state."""

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        pe = own["pe"]
        at, dist = halo(g, mail, "pe", pe), blocks.dist.astype(float)
        target, gain = np.full(len(pe), -1, np.int64), np.full(len(pe), LOWEST)
        for a, b, conn in _volumes(g, at, len(dist)):
            target[a:b], gain[a:b] = kernels.propose(conn, pe[a:b], dist, own["locked"][a:b] if locks else None, config)
        return {"pe": pe, "at": at, "target": target, "gain": gain}, letters(g, target=target, gain=gain), {"j": _cost(g, at, blocks.dist)}

    return run


def settling(blocks: Blocks):
    """The proposals that still pay when those before them (larger gain, then smaller id) are carried out."""

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        pe, at, dist = own["pe"], own["at"], blocks.dist.astype(float)
        target, gain = halo(g, mail, "target", own["target"]), halo(g, mail, "gain", own["gain"])
        ids = np.concatenate((g["ids"], g["halo"]))
        e = np.flatnonzero(target[g["src"]] >= 0)
        u, v = g["src"][e], g["dst"][e]
        earlier = (target[v] >= 0) & ((gain[v] > gain[u]) | ((gain[v] == gain[u]) & (ids[v] < ids[u])))
        there = np.where(earlier, target[v], at[v])
        change = np.bincount(u, weights=g["w"][e] * (dist[pe[u], there] - dist[target[u], there]), minlength=len(pe))
        movers = np.flatnonzero((own["target"] >= 0) & (np.rint(change) >= 0))
        return _moved(g, pe, movers, own["target"][movers], len(dist), lock=True)

    return run


def weighing(blocks: Blocks, config: Config, load: np.ndarray, strong: bool):
    """Vertices of overloaded blocks with a target and class of loss; and the weight of each block's classes."""
    if strong:
        limit = blocks.bound - 1
    else:
        gap = np.full(len(load), config.sigma_gap, np.int64)
        limit = blocks.bound - (np.minimum(gap, (blocks.bound - blocks.average) // 2) if config.sigma_mode == "scaled" else gap)
    takes = blocks.known & (load <= limit)
    over = blocks.known & (load > blocks.bound)
    lists = {int(p): np.flatnonzero(takes & (blocks.part == p)) for p in np.unique(blocks.part[blocks.known])}

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        pe, dist = own["pe"], blocks.dist.astype(float)
        at, k = halo(g, mail, "pe", pe), len(dist)
        movers = over[pe] & (config.heavy_den * g["c"] <= config.heavy_num * (load - blocks.average)[pe])
        found = []
        for a, b, conn in _volumes(g, at, k):
            v = np.flatnonzero(movers[a:b])
            if not len(v):
                continue
            conn, home, i = conn[v], pe[a:b][v], np.arange(len(v))
            if config.rebalance_objective == "cut":
                gain = kernels._integers(conn - conn[i, home][:, None])
            else:
                cost = kernels._integers(conn @ dist)
                gain = cost[i, home][:, None] - cost
            near = np.where((conn > 0) & takes[None, :], gain, LOWEST)
            near[i, home] = LOWEST
            target = near.argmax(1)
            best = near[i, target]
            noise = edge_noise_array(g["ids"][a:b][v], g["ids"][a:b][v], config.seed)
            for p, some in lists.items():  # without a neighbouring block that takes it: to any of its part
                lost = np.flatnonzero((best == LOWEST) & (blocks.part[home] == p)) if len(some) else np.zeros(0, np.int64)
                target[lost] = some[noise[lost] % max(1, len(some))] if len(lost) else target[lost]
                best[lost] = gain[lost, target[lost]]
            sure = best > LOWEST
            found.append(np.stack((v + a, target, kernels._bucket(best)), 1)[sure])
        v, target, bucket = np.concatenate(found).T if found else np.zeros((3, 0), np.int64)
        key, weight = _sums(pe[v] * BUCKETS + bucket, g["c"][v])
        return {"pe": pe, "v": v, "target": target, "bucket": bucket}, {}, {"j": _cost(g, at, blocks.dist), "key": key, "weight": weight}

    return run


def _sums(key: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keys, inverse = np.unique(key, return_inverse=True)
    out = np.zeros(len(keys), np.int64)
    np.add.at(out, inverse, c)
    return keys, out


def starts(told: list[dict]) -> list[dict[int, int]]:
    """For each shard and key (group * BUCKETS + bucket): the weight of the group in smaller buckets, and in this one in shards before."""
    total: dict[int, int] = {}
    for x in told:
        for key, weight in zip(x["key"].tolist(), x["weight"].tolist()):
            total[key] = total.get(key, 0) + weight
    upto, base, group = 0, {}, None
    for key in sorted(total):
        if key // BUCKETS != group:
            group, upto = key // BUCKETS, 0
        base[key], upto = upto, upto + total[key]
    out = []
    for x in told:
        keys = x["key"].tolist()
        out.append({key: base[key] for key in keys})
        for key, weight in zip(keys, x["weight"].tolist()):
            base[key] += weight
    return out


def _before(start: dict[int, int], key: np.ndarray, v: np.ndarray, c: np.ndarray) -> np.ndarray:
    names, inverse = np.unique(key, return_inverse=True)
    return np.array([start[x] for x in names.tolist()], np.int64)[inverse] + kernels._running((v,), key, c) if len(key) else np.zeros(0, np.int64)


def pouring(blocks: Blocks, load: np.ndarray, start: dict[int, dict[int, int]], strong: bool):
    """The movers that a block has to lose. Weakly, they move; strongly, the weight of each part's classes is told first."""

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        pe, v = own["pe"], own["v"]
        before = _before(start[s], pe[v] * BUCKETS + own["bucket"], v, g["c"][v])
        chosen = before < (load - blocks.bound)[pe[v]]
        v, target, bucket = v[chosen], own["target"][chosen], own["bucket"][chosen]
        if not strong:
            return _moved(g, pe, v, target, len(load))
        key, weight = _sums(blocks.part[pe[v]] * BUCKETS + bucket, g["c"][v])
        return {"pe": pe, "v": v, "bucket": bucket}, {}, {"key": key, "weight": weight}

    return run


def placing(blocks: Blocks, load: np.ndarray, start: dict[int, dict[int, int]]):
    """Movers as intervals of a line of each part, to the block with room whose interval holds theirs."""

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        pe, v = own["pe"], own["v"]
        part, c = blocks.part[pe[v]], g["c"][v]
        at = _before(start[s], part * BUCKETS + own["bucket"], v, c)
        to = np.full(len(v), -1, np.int64)
        for p in np.unique(part):
            room = np.flatnonzero(blocks.known & (blocks.part == p) & (load < blocks.bound))
            if not len(room):
                continue
            own_part = np.flatnonzero(part == p)
            high = np.cumsum((blocks.bound - load)[room])
            low = high - (blocks.bound - load)[room]
            slot = np.searchsorted(high, at[own_part], side="right")
            good = slot < len(room)
            slot = np.minimum(slot, len(room) - 1)
            good &= (at[own_part] >= low[slot]) & (at[own_part] + c[own_part] <= high[slot])
            to[own_part[good]] = room[slot[good]]
        return _moved(g, pe, v[to >= 0], to[to >= 0], len(load))

    return run


def fitting(blocks: Blocks, load: np.ndarray, room: dict[int, int]):
    """Of each part, the heaviest vertex of its overloaded blocks that fits into the room given."""
    over = blocks.known & (load > blocks.bound)

    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        best = {}
        for p, most in room.items():
            v = np.flatnonzero(over[own["pe"]] & (blocks.part[own["pe"]] == p) & (g["c"] <= most))
            if len(v):
                x = v[g["c"][v].argmax()]  # the least id among equals
                best[p] = (int(g["c"][x]), -int(g["ids"][x]))
        return own, letters(g, pe=own["pe"]), {"best": best}

    return run


def forcing(k: int, to: dict[int, int]):
    def run(g: dict, s: int, own: dict, mail: dict) -> tuple[dict, dict, dict]:
        v = np.flatnonzero(np.isin(g["ids"], list(to)))
        return _moved(g, own["pe"], v, np.array([to[x] for x in g["ids"][v].tolist()], np.int64), k)

    return run


def refine_shards(graph: TaskGraph, mapping: DataFrame, bounds: dict[int, tuple[int, int, int]], dist: np.ndarray, config: Config, clock: Clock, level: int) -> DataFrame:
    """id, pe: the loop of taskmap.plans.refine."""
    with clock.phase("refine", level):
        blocks = Blocks.of(bounds, dist)
        shards = Shards(graph, "pe", mapping.select("id", F.col("pe").alias("value")))
        out = shards.together(lambda at: _loop(at, blocks, config), lambda g, own: (g["ids"], own["pe"]), "pe", "int")
        shards.close()
        return out


def _loop(shards: Shards | Ring, blocks: Blocks, config: Config) -> DataFrame | dict:
    """The best state that the loop meets."""
    k, release = len(blocks.dist), shards.release
    count_loads = lambda g, s, own, mail: ({"pe": own["pe"], "locked": np.zeros(len(own["pe"]), bool)}, letters(g, pe=own["pe"]), {"loads": _loads(g, own["pe"], k)})
    now, told = shards.step(shards.first, count_loads)
    load = sum((x["loads"] for x in told), np.zeros(k, np.int64))

    def opened(table: DataFrame, load: np.ndarray, own: Config, strong: bool, locks: bool) -> tuple[DataFrame, list[dict], State]:
        excess = blocks.excess(load)
        run = proposing(blocks, own, locks) if excess <= 0 else weighing(blocks, own, load, strong)
        middle, told = shards.step(table, run)
        return middle, told, State(excess <= 0, sum(x["j"] for x in told), excess)

    def ended(table: DataFrame, middle: DataFrame, told: list[dict], load: np.ndarray, feasible: bool, strong: bool) -> tuple[DataFrame, int, np.ndarray]:
        """The state after the round that middle began."""
        if feasible:
            after, told = shards.step(middle, settling(blocks))
        else:
            poured, told = shards.step(middle, pouring(blocks, load, dict(enumerate(starts(told))), strong))
            after = poured
            if strong:
                after, told = shards.step(poured, placing(blocks, load, dict(enumerate(starts(told)))))
                release(poured)
                if not sum(x["count"] for x in told):
                    after, told = forced(after, load)
        return after, sum(x["count"] for x in told), sum((x["loads"] for x in told), np.zeros(k, np.int64))

    def forced(table: DataFrame, load: np.ndarray) -> tuple[DataFrame, list[dict]]:
        """The last resort: one mover for each part and round, the heaviest that fits, to the roomiest block."""
        free = np.where(blocks.known & (load < blocks.bound), blocks.bound - load, 0)
        roomiest = {int(p): int(np.where(blocks.part == p, free, 0).argmax()) for p in np.unique(blocks.part[free > 0])}
        asked, told = shards.step(table, fitting(blocks, load, {p: int(free[pe]) for p, pe in roomiest.items()}))
        best = {p: max(x["best"][p] for x in told if p in x["best"]) for p in roomiest if any(p in x["best"] for x in told)}
        after, told = shards.step(asked, forcing(k, {-x[1]: roomiest[p] for p, x in best.items()}))
        release(table, asked)
        return after, told

    best, best_load, held = now, load, None
    for p in range(config.passes):
        own = pass_config(config, p)
        now, load = best, best_load
        patience = weak = held_back = 0
        middle, told, state = opened(now, load, own, weak >= config.max_weak, False)
        held = held or state
        for _ in range(config.rounds):
            if patience >= config.patience:
                break
            patience += 1
            waited, feasible = held_back, state.feasible
            strong = weak >= config.max_weak
            after, count, load = ended(now, middle, told, load, feasible, strong)
            weak = 0 if feasible or strong else weak + 1
            held_back = count if feasible else 0
            release(middle, *([now] if now is not best else []))
            now = after
            middle, told, state = opened(now, load, own, weak >= config.max_weak, True)
            take, anew = accepts(held, state, config.phi)
            if take:
                release(best)
                best, best_load, held = now, load, state
            if anew:
                patience = 0
            if not count and feasible and not waited and not anew:
                break  # nothing moves and nothing was locked: every further round is the same
        release(middle, *([now] if now is not best else []))
    return best
