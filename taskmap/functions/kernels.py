"""Small graphs in one task: the same algorithms over arrays.

A graph of a few thousand vertices is finished by one task, which saves thousands of tiny stages; larger ones never come
here (Config.small_edges). Semantics follow the relational operators: integer weights, total orders, deterministic noise.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from taskmap.config import Config
from taskmap.operators.noise import edge_noise_array
from taskmap.topology import Topology, load_bound


@dataclass
class Small:
    """Vertices 0..n-1 with weights c; directed edges src, dst, w (both directions, sorted by src)."""

    c: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    w: np.ndarray

    @classmethod
    def of(cls, ids: np.ndarray, c: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> tuple[Small, np.ndarray]:
        """From tables in any order; the ids in the order of the vertex numbers come back with it."""
        order = np.argsort(ids)
        ids = ids[order]
        s, t = np.searchsorted(ids, src), np.searchsorted(ids, dst)
        by = np.lexsort((t, s))
        return cls(c[order].astype(np.int64), s[by], t[by], w[by].astype(np.int64)), ids

    @property
    def n(self) -> int:
        return len(self.c)

    def rows(self) -> np.ndarray:
        """Where each vertex's edges begin; one more entry ends the last."""
        return np.append(0, np.cumsum(np.bincount(self.src, minlength=self.n)))

    def contract(self, coarse: np.ndarray) -> Small:
        """coarse numbers vertices 0.. without gaps."""
        k = int(coarse.max()) + 1 if len(coarse) else 0
        c = np.bincount(coarse, weights=self.c, minlength=k).astype(np.int64)
        narrow = coarse.astype(np.int32) if k < 1 << 31 else coarse
        s, t = narrow[self.src], narrow[self.dst]
        keep = s != t
        key = s[keep].astype(np.int64) * max(k, 1) + t[keep]
        del s, t
        pair, w = _summed(key, self.w[keep])
        return Small(c, pair // max(k, 1), pair % max(k, 1), w)

    def within(self, chosen: np.ndarray) -> tuple[Small, np.ndarray]:
        """The subgraph of the chosen vertices, and their numbers here."""
        number = np.cumsum(chosen) - 1
        keep = chosen[self.src] & chosen[self.dst]
        return Small(self.c[chosen], number[self.src[keep]], number[self.dst[keep]], self.w[keep]), np.flatnonzero(chosen)


def objective(g: Small, pe: np.ndarray, dist: np.ndarray) -> int:
    s, t = pe[g.src], pe[g.dst]
    if dist.diagonal().any():
        return int((g.w * dist[s, t]).sum())
    cut = np.flatnonzero(s != t)  # the others cost nothing
    return int((g.w[cut] * dist[s[cut], t[cut]]).sum())


def edge_cut(g: Small, pe: np.ndarray) -> int:
    return int(g.w[pe[g.src] != pe[g.dst]].sum()) // 2


#: Edges that the rating of a matching looks at at once.
PORTION = 1 << 20


def _summed(key: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys in order, and the sum of w for each."""
    order = np.argsort(key)
    key = key[order]
    starts = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    return key[starts], np.add.reduceat(w[order], starts) if len(key) else w


def _best_of_runs(group: np.ndarray, keys: tuple[np.ndarray, ...]) -> np.ndarray:
    """As _best_by where equal groups are next to each other: no sorting."""
    at = np.arange(len(group))
    for key in keys:
        if not len(at):
            return at
        own, x = group[at], key[at]
        starts = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
        top = np.maximum.reduceat(x, starts)
        if x.dtype.kind == "f" and np.isnan(top).any():
            return _best_by(group, keys)
        at = at[x == np.repeat(top, np.diff(np.append(starts, len(at))))]
    own = group[at]
    return at[np.append(own[1:] != own[:-1], True)] if len(at) else at


def _best_by(group: np.ndarray, keys: tuple[np.ndarray, ...]) -> np.ndarray:
    """The index of the largest row of each group, by keys (most significant first)."""
    if not len(group):
        return np.zeros(0, np.int64)
    order = np.lexsort((*reversed(keys), group))
    return order[np.append(group[order][1:] != group[order][:-1], True)]


def matching(g: Small, bound: int, config: Config) -> np.ndarray:
    """coarse numbers by rounds of mutual preference, then leaves, twins, relatives and isolated vertices."""
    n = g.n
    mate = np.full(n, -1, np.int64)
    squared = config.rating == "squared_over_product"

    def preferred(edges: np.ndarray) -> np.ndarray:
        """The best of the edges at each vertex, from portions that end between vertices."""
        found, a = [np.zeros(0, np.int64)], 0
        while a < len(edges):
            last = g.src[edges[min(a + PORTION, len(edges)) - 1]]
            b = int(np.searchsorted(edges, np.searchsorted(g.src, last, "right")))
            e = edges[a:b]
            u, v = g.src[e], g.dst[e]
            rating = g.w[e].astype(float)
            if squared:
                rating = rating**2 / (g.c[u] * g.c[v])
            found.append(e[_best_of_runs(u, (rating, edge_noise_array(u, v, config.seed), v))])
            a = b
        return np.concatenate(found)

    open_ = np.concatenate([np.zeros(0, np.int64)] + [a + np.flatnonzero(g.c[g.src[a : a + PORTION]] + g.c[g.dst[a : a + PORTION]] <= bound) for a in range(0, len(g.src), PORTION)])
    for r in range(config.match_rounds):
        if r:
            open_ = open_[(mate[g.src[open_]] < 0) & (mate[g.dst[open_]] < 0)]
        best = preferred(open_)
        pref = np.full(n, -1, np.int64)
        pref[g.src[best]] = g.dst[best]
        v = np.flatnonzero(pref >= 0)
        both = v[pref[pref[v]] == v]
        if not len(both):
            break
        mate[both] = pref[both]
        if (mate >= 0).sum() > config.match_target * n:
            break

    def pair(members: np.ndarray, key: np.ndarray) -> None:
        order = np.lexsort((members, key))
        m, k = members[order], key[order]
        starts = np.flatnonzero(np.append(True, k[1:] != k[:-1])) if len(k) else np.zeros(0, np.int64)
        place = np.arange(len(m)) - np.repeat(starts, np.diff(np.append(starts, len(m))))
        first = np.flatnonzero((place[:-1] % 2 == 0) & (k[1:] == k[:-1])) if len(m) > 1 else np.zeros(0, np.int64)
        first = first[g.c[m[first]] + g.c[m[first + 1]] <= bound]
        mate[m[first]], mate[m[first + 1]] = m[first + 1], m[first]

    enough = lambda: (mate >= 0).sum() > config.match_target * n
    degree = np.bincount(g.src, minlength=n)
    starts = g.rows()[:-1]
    if not enough():
        v = np.flatnonzero((degree == 1) & (mate < 0))
        pair(v, g.dst[starts[v]])
    if not enough():
        v = np.flatnonzero((degree > 0) & (mate < 0))
        known: dict[bytes, int] = {}
        pair(v, np.array([known.setdefault(g.dst[starts[i] : starts[i] + degree[i]].tobytes(), len(known)) for i in v], np.int64))
    if not enough():
        best = preferred(np.flatnonzero(mate[g.src] < 0))
        pair(g.src[best], g.dst[best])
    if not enough():
        v = np.flatnonzero((degree == 0) & (mate < 0))
        pair(v, np.zeros(len(v), np.int64))
    label = np.where(mate >= 0, np.minimum(mate, np.arange(n)), np.arange(n))
    return (np.cumsum(label == np.arange(n)) - 1)[label]


def clustering(g: Small, most: int, config: Config) -> np.ndarray:
    """Coarse numbers by label propagation on volume: half of the vertices in a round choose, clusters admit by volume."""
    n = g.n
    label = np.arange(n)
    for r in range(config.cluster_rounds):
        full = np.bincount(label, weights=g.c, minlength=n).astype(np.int64)
        turn = edge_noise_array(np.arange(n), np.arange(n), config.seed + r) % 2 == 0
        e = np.flatnonzero(turn[g.src])
        pair, inverse = np.unique(g.src[e] * n + label[g.dst[e]], return_inverse=True)
        volume = np.bincount(inverse, weights=g.w[e], minlength=len(pair))
        v, to = pair // n, pair % n
        room = (to == label[v]) | (full[to] + g.c[v] <= most)
        v, to, volume = v[room], to[room], volume[room]
        best = _best_by(v, (volume, -to))
        v, to, volume = v[best], to[best], volume[best]
        moving = to != label[v]
        v, to, volume = v[moving], to[moving], volume[moving]
        upto = _running((-volume, v), to, g.c[v]) + g.c[v]
        admitted = full[to] + upto <= most
        label = label.copy()
        label[v[admitted]] = to[admitted]
    least = np.full(n, n)
    np.minimum.at(least, label, np.arange(n))
    return np.unique(least[label], return_inverse=True)[1]


def connectivity(g: Small, pe: np.ndarray, k: int) -> np.ndarray:
    """n x k volumes from vertices into blocks."""
    return np.bincount(g.src * k + pe[g.dst], weights=g.w, minlength=g.n * k).reshape(g.n, k)


#: Entries of the tables of vertices by blocks that are held at once: rows are taken in portions.
TABLE = 1 << 21


def edges_of(rows: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The edges of vertices v, one after another, and for each the place of its vertex in v."""
    count = rows[v + 1] - rows[v]
    at = np.repeat(np.arange(len(v)), count)
    return np.arange(len(at)) + (rows[v] - np.cumsum(count) + count)[at], at


def portions(g: Small, pe: np.ndarray, rows: np.ndarray, v: np.ndarray, k: int) -> Iterator[tuple[slice, np.ndarray]]:
    """The connectivity of vertices v as tables of at most TABLE entries: where they are in v, and their rows."""
    if 3 * len(v) > g.n and g.n * k <= TABLE:  # most of a small graph: sooner all of it
        yield slice(0, len(v)), connectivity(g, pe, k)[v]
        return
    step = max(1, TABLE // k)
    for a in range(0, len(v), step):
        own = v[a : a + step]
        e, at = edges_of(rows, own)
        yield slice(a, a + step), np.bincount(at * k + pe[g.dst[e]], weights=g.w[e], minlength=len(own) * k).reshape(len(own), k)


def _integers(x: np.ndarray) -> np.ndarray:
    return np.rint(x).astype(np.int64)


LOWEST = np.iinfo(np.int64).min


def propose(conn: np.ndarray, pe: np.ndarray, dist: np.ndarray, locked: np.ndarray | None, config: Config) -> tuple[np.ndarray, np.ndarray]:
    """Targets (-1: none) and gains of the best moves that pass the first filter."""
    n = len(pe)
    cost = _integers(conn @ dist)
    own = np.arange(n)
    gain = np.where(conn > 0, cost[own, pe][:, None] - cost, LOWEST)
    gain[own, pe] = LOWEST
    target = gain.argmax(1)  # the lowest PE among equals
    best = gain[own, target]
    allowed = best >= 0
    if config.filter_mode == "relaxed":
        allowed |= (best > LOWEST) & (-np.maximum(best, LOWEST + 1) < np.floor(config.relaxed_c * conn[own, pe]))
    if locked is not None:
        allowed &= ~locked
    return np.where(allowed, target, -1), best


def moves(g: Small, pe: np.ndarray, rows: np.ndarray, dist: np.ndarray, v: np.ndarray, config: Config) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Those of the vertices v that propose has a target for, with the targets and gains.

    Where vertices touch few of many blocks, only the blocks that they touch are looked at.
    """
    k, found = len(dist), []
    step = max(1, TABLE // (16 if k > 16 else k))
    for a in range(0, len(v), step):
        own = v[a : a + step]
        part = _few_blocks(g, pe, rows, dist, own, config) if k > 16 else None
        if part is not None:
            found.append(part)
            continue
        for at, conn in portions(g, pe, rows, own, k):
            u = own[at]
            target, gain = propose(conn, pe[u], dist, None, config)
            some = target >= 0
            found.append((u[some], target[some], gain[some]))
    if not found:
        none = np.zeros(0, np.int64)
        return none, none, none
    return tuple(np.concatenate(x) for x in zip(*found))


def _touched(g: Small, pe: np.ndarray, rows: np.ndarray, v: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Place in v, block and volume, by place and block, of the blocks next to each vertex and of its own."""
    e, at = edges_of(rows, v)
    key, w = np.concatenate((at * k + pe[g.dst[e]], np.arange(len(v)) * k + pe[v])), np.append(g.w[e], np.zeros(len(v), g.w.dtype))
    if k <= 16:
        has = np.bincount(key, minlength=len(v) * k)
        pair = np.flatnonzero(has)
        volume = np.bincount(key, weights=w, minlength=len(v) * k)[pair].astype(np.int64)
    else:
        pair, volume = _summed(key, w)
    return pair // k, pair % k, volume


def _few_blocks(g: Small, pe: np.ndarray, rows: np.ndarray, dist: np.ndarray, v: np.ndarray, config: Config) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """As moves, over the pairs of a vertex and a block that it touches; None where there are too many of them."""
    k, home = len(dist), pe[v]
    u, block, volume = _touched(g, pe, rows, v, k)
    count = np.bincount(u, minlength=len(v))
    if (count * count).sum() > len(v) * k * k // 64:
        return None
    first = np.cumsum(count) - count
    # each pair against all of its vertex
    times = count[u]
    i = np.repeat(np.arange(len(u)), times)
    j = np.arange(len(i)) + np.repeat(first[u] - np.cumsum(times) + times, times)
    cost = _integers(np.bincount(i, weights=volume[j] * dist[block[j], block[i]], minlength=len(u)))
    here = np.flatnonzero(block == home[u])
    away = np.flatnonzero((block != home[u]) & (volume > 0))
    gain = cost[here[u[away]]] - cost[away]
    best = _best_of_runs(u[away], (gain, -block[away]))  # the lowest PE among equals
    u, target, gain = u[away[best]], block[away[best]], gain[best]
    allowed = gain >= 0
    if config.filter_mode == "relaxed":
        allowed |= -gain < np.floor(config.relaxed_c * volume[here[u]])
    return v[u[allowed]], target[allowed], gain[allowed]


def proposals(g: Small, pe: np.ndarray, rows: np.ndarray, dist: np.ndarray, locked: np.ndarray | None, config: Config) -> tuple[np.ndarray, np.ndarray]:
    """Targets and gains as propose tells them, from the vertices with a neighbour in another block: the others have no move."""
    target, gain = np.full(g.n, -1, np.int64), np.full(g.n, LOWEST)
    v = np.flatnonzero(np.bincount(g.src[pe[g.src] != pe[g.dst]], minlength=g.n))
    v, to, best = moves(g, pe, rows, dist, v if locked is None else v[~locked[v]], config)
    target[v], gain[v] = to, best
    return target, gain


class Front:
    """A mapping with its cost, its blocks' loads and each vertex's number of edges into other blocks, kept as vertices move.

    A round then looks at the vertices between blocks and at those that move, not at all edges. Distances are symmetric.
    """

    def __init__(self, g: Small, pe: np.ndarray, dist: np.ndarray, rows: np.ndarray):
        self.g, self.dist, self.rows, self.k = g, dist, rows, len(dist)
        self.mark = np.zeros(g.n, bool)
        self.strength = np.bincount(g.src, weights=g.w, minlength=g.n).astype(np.int64)
        self.target, self.gain = np.full(g.n, -1, np.int64), np.zeros(g.n, np.int64)  # of proposals, while they are looked at
        self.put(pe)

    def put(self, pe: np.ndarray) -> None:
        g = self.g
        self.pe = pe.copy()
        self.j = objective(g, pe, self.dist)
        self.load = np.bincount(pe, weights=g.c, minlength=self.k).astype(np.int64)
        self.away = np.bincount(g.src[pe[g.src] != pe[g.dst]], minlength=g.n)

    def restore(self, kept: tuple) -> None:
        self.pe, self.j, self.load, self.away = (x.copy() if isinstance(x, np.ndarray) else x for x in kept)

    def held(self) -> tuple:
        return self.pe.copy(), self.j, self.load.copy(), self.away.copy()

    def movers(self, locked: np.ndarray, config: Config) -> tuple[np.ndarray, np.ndarray]:
        """The best moves that are left when neighbours earlier in the order count as moved. Vertices of locked stay."""
        g, pe, k = self.g, self.pe, self.k
        self.mark[locked] = True
        v = np.flatnonzero(self.away)
        v = v[~self.mark[v]]
        self.mark[locked] = False
        v, to, best = moves(g, pe, self.rows, self.dist, v, config)
        self.target[v], self.gain[v] = to, best
        e, at = edges_of(self.rows, v)
        near = g.dst[e]
        theirs, ours, other = self.target[near], best[at], self.gain[near]
        earlier = (theirs >= 0) & ((other > ours) | ((other == ours) & (near < v[at])))
        there = np.where(earlier, theirs, pe[near])
        flat = self.dist.ravel()
        change = np.bincount(at, weights=g.w[e] * (flat[(pe[v] * k)[at] + there] - flat[(to * k)[at] + there]), minlength=len(v))
        self.target[v] = -1
        stay = _integers(change) >= 0
        return v[stay], to[stay]

    def move(self, v: np.ndarray, to: np.ndarray) -> None:
        if not len(v):
            return
        g, pe, k = self.g, self.pe, self.k
        e, at = edges_of(self.rows, v)
        near, w, flat = g.dst[e], g.w[e], self.dist.ravel()
        old, before = pe[v], pe[near]
        self.load += (np.bincount(to, weights=g.c[v], minlength=k) - np.bincount(old, weights=g.c[v], minlength=k)).astype(np.int64)
        pe[v] = to
        after = pe[near]
        self.mark[v] = True
        both = self.mark[near]  # an edge between movers is met from either end
        self.mark[v] = False
        self.j += int((w * (flat[to[at] * k + after] - flat[old[at] * k + before]) * np.where(both, 1, 2)).sum())
        cut = after != to[at]
        change = cut.astype(np.int64) - (before != old[at])
        one = np.flatnonzero((change != 0) & ~both)
        np.add.at(self.away, near[one], change[one])
        self.away[v] = np.bincount(at, weights=cut, minlength=len(v))


def _bucket(gain: np.ndarray) -> np.ndarray:
    loss = np.maximum(-gain, 1)
    return np.where(gain > 0, 0, np.where(gain == 0, 1, 2 + np.frexp(loss.astype(float))[1] - 1))


def _running(keys: tuple[np.ndarray, ...], group: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The weight before each row within its group, in the order of keys."""
    order = np.lexsort((*reversed(keys), group))
    sums = np.cumsum(c[order]) - c[order]
    new = np.append(True, group[order][1:] != group[order][:-1]) if len(group) else np.zeros(0, bool)
    base = np.maximum.accumulate(np.where(new, np.arange(len(group)), 0)) if len(group) else np.zeros(0, np.int64)
    out = np.empty(len(c), np.int64)
    out[order] = sums - sums[base] if len(group) else sums
    return out


def _any_of(blocks: np.ndarray, v: np.ndarray, config: Config) -> np.ndarray:
    return blocks[edge_noise_array(v, v, config.seed) % len(blocks)]


def _near(g: Small, pe: np.ndarray, rows: np.ndarray, v: np.ndarray, k: int, pairs: bool) -> Iterator[tuple[slice, np.ndarray | tuple]]:
    """Portions of vertices v with their connectivity: a table, or the pairs of a vertex and a block that it touches."""
    if not pairs:
        yield from portions(g, pe, rows, v, k)
        return
    step = max(1, TABLE // 16)
    for a in range(0, len(v), step):
        yield slice(a, a + step), _touched(g, pe, rows, v[a : a + step], k)


def rebalance(g: Small, pe: np.ndarray, rows: np.ndarray, dist: np.ndarray, bound: np.ndarray, average: float, config: Config, strong: bool, front: Front | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Movers and their new blocks. What a front of the mapping holds need not be counted again."""
    k = len(bound)
    front = front or Front(g, pe, dist, rows)
    load = front.load
    over = load > bound
    v = np.flatnonzero(over[pe])
    v = v[config.heavy_den * g.c[v] <= config.heavy_num * (load[pe[v]] - average)]
    if strong:
        limit = bound - 1
    elif config.sigma_mode == "scaled":
        limit = bound - np.minimum(config.sigma_gap, (bound - int(average)) // 2)
    else:
        limit = bound - config.sigma_gap
    accepts = load <= limit
    none = np.zeros(0, np.int64)
    if not len(v) or not accepts.any():
        return none, none
    eligible = np.flatnonzero(accepts)
    target, best = np.full(len(v), -1), np.empty(len(v), np.int64)
    cut = config.rebalance_objective == "cut"
    outer = np.flatnonzero(front.away[v])  # the others have no block near
    for at, found in _near(g, pe, rows, v[outer], k, cut):
        own = outer[at]
        if cut:
            i, block, volume = found
            home = pe[v[own]]
            inside = np.zeros(len(own), np.int64)
            here = block == home[i]
            inside[i[here]] = volume[here]
            near = np.flatnonzero(~here & (volume > 0) & accepts[block])
            gain = volume[near] - inside[i[near]]
            top = _best_of_runs(i[near], (gain, -block[near]))  # the lowest block among equals
            best[own] = -inside
            target[own[i[near[top]]]], best[own[i[near[top]]]] = block[near[top]], gain[top]
            continue
        home, i = pe[v[own]], np.arange(len(own))
        cost = _integers(found @ dist)
        gain = cost[i, home][:, None] - cost
        near = np.where((found > 0) & accepts[None, :], gain, LOWEST)
        near[i, home] = LOWEST
        to = near.argmax(1)
        lost = near[i, to] == LOWEST
        to[lost] = _any_of(eligible, v[own][lost], config)
        target[own], best[own] = to, gain[i, to]
    inner = front.away[v] == 0
    best[inner] = -front.strength[v[inner]]
    lost = np.flatnonzero(target < 0)
    target[lost] = _any_of(eligible, v[lost], config)
    if not cut:
        u = v[inner]
        best[inner] = _integers(front.strength[u] * (dist[pe[u], pe[u]] - dist[pe[u], target[inner]]))
    bucket = _bucket(best)
    before = _running((bucket,), pe[v].astype(np.int32), g.c[v])  # v is in order
    chosen = before < load[pe[v]] - bound[pe[v]]
    v, target, bucket = v[chosen], target[chosen], bucket[chosen]
    if not strong:
        return v, target
    start = _running((bucket, v), np.zeros(len(v), np.int64), g.c[v])
    room = np.flatnonzero(load < bound)
    high = np.cumsum(bound[room] - load[room])
    low = high - (bound[room] - load[room])
    slot = np.searchsorted(high, start, side="right")
    good = slot < len(room)
    slot = np.minimum(slot, len(room) - 1)
    good &= (start >= low[slot]) & (start + g.c[v] <= high[slot])
    return v[good], room[slot[good]]


@dataclass
class State:
    feasible: bool
    j: int
    heaviest: int


def accepts(old: State, new: State, phi: float) -> tuple[bool, bool]:
    """Whether the candidate replaces the incumbent, and whether patience starts anew.

    A feasible one beats one that isn't; two feasible ones compare by cost, others by the heaviest excess. The cost before
    the replacement decides whether the improvement counts.
    """
    if new.feasible and not old.feasible:
        return True, True
    if new.feasible and old.feasible:
        return new.j < old.j, new.j < phi * old.j
    if not new.feasible and not old.feasible:
        better = new.heaviest < old.heaviest
        return better, better
    return False, False


def pass_config(config: Config, p: int) -> Config:
    """Of the p-th pass: other choices at random and, with the relaxed filter, other losses allowed, so that passes differ."""
    return config.but(seed=config.seed + p, relaxed_c=config.relaxed_c * (1 + p % 4)) if p else config


def refine(g: Small, pe: np.ndarray, dist: np.ndarray, bound: np.ndarray, config: Config) -> np.ndarray:
    """The whole loop: label propagation while balanced, else weak rebalancing up to twice and then strong."""
    k = len(bound)
    average = float(g.c.sum()) / max(1, k)
    dist, rows = dist.astype(float), g.rows()
    none = np.zeros(0, np.int64)
    front = Front(g, pe, dist, rows)

    def state() -> State:
        excess = int((front.load - bound).max()) if k else 0
        return State(excess <= 0, front.j, excess)

    best, held, current = front.held(), state(), state()
    for p in range(config.passes):
        own = pass_config(config, p)
        i = weak = rounds = 0
        locked = none
        while i < config.patience and rounds < config.rounds:
            i, rounds = i + 1, rounds + 1
            if current.feasible:
                movers, to = front.movers(locked, own)
                locked = movers
                weak = 0
            else:
                strong = weak >= config.max_weak
                movers, to = rebalance(g, front.pe, rows, dist, bound, average, own, strong, front)
                if strong and not len(movers):
                    movers, to = _largest_first(g, front.pe, bound)
                weak = 0 if strong else weak + 1
                locked = none
            front.move(movers, to)
            current = state()
            take, anew = accepts(held, current, config.phi)
            if take:
                best, held = front.held(), current
            if anew:
                i = 0
        if p + 1 < config.passes:
            front.restore(best)
            current = held
    return best[0]


def improve(g: Small, pe: np.ndarray, dist: np.ndarray, bound: np.ndarray, config: Config) -> np.ndarray:
    """The refinement of a level: the loop, and the local search where the settings ask for it."""
    pe = refine(g, pe, dist, bound, config)
    return local_search(g, pe, dist, bound) if config.local_search == "fm" else pe


def local_search(g: Small, pe: np.ndarray, dist: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """Passes of single moves, best gain first and losses too, until a pass gains nothing.

    In a pass each vertex moves at most once, into a block of a neighbour that has room; what is left of the pass is its
    prefix of least cost. Blocks never pass their bounds by a move, so no excess grows. Edges between moved vertices stay as
    they are to the pass's end: once they alone cost as much as the best prefix, no later one is better, and the pass ends.
    """
    k, rows, n = len(bound), g.rows(), g.n
    d = (dist.astype(np.int64) if (dist == np.rint(dist)).all() else dist).tolist()
    apart = d[0][1] if k > 1 else 0
    flat = bool((dist == apart * (1 - np.eye(k))).all())  # all other blocks are equally far
    load = np.bincount(pe, weights=g.c, minlength=k).astype(np.int64).tolist()
    at, c, most = pe.tolist(), g.c.tolist(), bound.tolist()
    edges: list[list[tuple[int, int]] | None] = [None] * n  # of the vertices looked at so far
    volumes: list[dict[int, int] | None] = [None] * n  # into blocks

    def around(v: int) -> list[tuple[int, int]]:
        e = slice(rows[v], rows[v + 1])
        edges[v] = list(zip(g.dst[e].tolist(), g.w[e].tolist()))
        return edges[v]

    def back(v: int, a: int, b: int) -> None:
        """Takes the move from a to b back."""
        for u, w in edges[v]:
            near = volumes[u]
            if near is not None:
                if left := near[b] - w:
                    near[b] = left
                else:
                    del near[b]
                near[a] = near.get(a, 0) + w
        load[b] -= c[v]
        load[a] += c[v]
        at[v] = a

    cost = objective(g, pe, dist) / 2
    while True:
        locked = bytearray(n)
        queue: list[tuple] = []
        told: dict[int, tuple] = {}  # the entry of the queue that holds for a vertex
        waiting: list[set[int]] = [set() for _ in range(k)]
        now = np.array(at)
        border = np.bincount(g.src, weights=g.w * (now[g.src] != now[g.dst]), minlength=n)
        todo = np.flatnonzero(border).tolist()
        moved: list[tuple[int, int]] = []
        total = top = fixed = 0
        kept = 0
        while True:
            # queues each vertex's best move that fits, and notes where a better one waits for room
            for v in todo:
                own, weight, near = at[v], c[v], volumes[v]
                if near is None:
                    near = volumes[v] = {}
                    for u, w in edges[v] or around(v):
                        near[at[u]] = near.get(at[u], 0) + w
                if len(near) == 1 and own in near:
                    told.pop(v, None)
                    continue
                best = to = full = None
                base = near.get(own, 0) if flat else sum([w * d[x][own] for x, w in near.items()])
                for t, w in near.items():
                    if t == own or w <= 0:
                        continue
                    gain = apart * (w - base) if flat else base - sum([y * d[x][t] for x, y in near.items()])
                    if load[t] + weight > most[t]:
                        full = [(gain, t)] if full is None else [*full, (gain, t)]
                    elif to is None or gain > best or (gain == best and t < to):
                        best, to = gain, t
                if full is not None:
                    for gain, t in full:
                        if to is None or gain > best:
                            waiting[t].add(v)
                if to is None:
                    told.pop(v, None)
                elif told.get(v) != (entry := (-best, v, to)):
                    told[v] = entry
                    heapq.heappush(queue, entry)
            if not queue or fixed >= cost - top >= 0:
                break
            entry = heapq.heappop(queue)
            loss, v, b = entry
            if locked[v] or told.get(v) != entry:
                todo = ()
                continue
            if load[b] + c[v] > most[b]:
                del told[v]
                todo = (v,)
                continue
            a = at[v]
            locked[v] = 1
            moved.append((v, a))
            again = {u for u in waiting[a] if not locked[u]}
            waiting[a] = set()
            for u, w in edges[v] or around(v):
                near = volumes[u]
                if near is not None:
                    if left := near[a] - w:
                        near[a] = left
                    else:
                        del near[a]
                    near[b] = near.get(b, 0) + w
                if locked[u]:
                    fixed += w * d[b][at[u]]
                else:
                    again.add(u)
            load[a] -= c[v]
            load[b] += c[v]
            at[v] = b
            total -= loss
            if total > top:
                top, kept = total, len(moved)
            todo = sorted(again)
        for v, a in reversed(moved[kept:]):
            back(v, a, at[v])
        cost -= top
        if not kept:
            return np.array(at, np.int64)


def _largest_first(g: Small, pe: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The last resort: vertices of overloaded blocks, heaviest first, go where they fit with least load."""
    load = np.bincount(pe, weights=g.c, minlength=len(bound)).astype(np.int64)
    movers, to = [], []
    for b in np.flatnonzero(load > bound):
        inside = np.flatnonzero(pe == b)
        for v in inside[np.lexsort((inside, -g.c[inside]))]:
            if load[b] <= bound[b]:
                break
            free = bound - load - g.c[v]
            free[b] = -1
            t = int(free.argmax())
            if free[t] >= 0 and g.c[v] > 0:
                load[b] -= g.c[v]
                load[t] += g.c[v]
                movers.append(v), to.append(t)
    return np.array(movers, np.int64), np.array(to, np.int64)


def grow(g: Small, bound: np.ndarray, config: Config) -> np.ndarray:
    """A simple k-way start: blocks grow one after another from a vertex far from the last, up to their share."""
    n, k = g.n, len(bound)
    pe = np.full(n, -1, np.int64)
    rows = g.rows()
    left, share = int(g.c.sum()), 0
    start_order = np.argsort(edge_noise_array(np.arange(n), np.arange(n), config.seed), kind="stable")
    cursor = 0
    for b in range(k):
        share = -(-left // (k - b))
        goal = min(int(bound[b]), share)
        load = 0
        queue: list[tuple[int, int]] = []
        pull = np.zeros(n, np.int64)
        while load < goal:
            v = -1
            while queue:
                p, u = heapq.heappop(queue)
                if pe[u] == -1 and -p == pull[u]:
                    v = u
                    break
            if v < 0:
                if load and cursor < n and b < k - 1 and load * 10 >= goal * 9:
                    break
                while cursor < n and pe[start_order[cursor]] != -1:
                    cursor += 1
                if cursor == n:
                    break
                v = int(start_order[cursor])
                if load == 0 and b:
                    # begin next to what is placed already: the open vertex with most volume into it
                    touched = np.flatnonzero((pe[g.src] >= 0) & (pe[g.dst] == -1))
                    if len(touched):
                        into = np.bincount(g.dst[touched], weights=g.w[touched], minlength=n)
                        v = int(into.argmax())
            if load and load + g.c[v] > bound[b]:
                pe[v] = -2  # does not fit here
                continue
            pe[v] = b
            load += int(g.c[v])
            for e in range(rows[v], rows[v + 1]):
                u = g.dst[e]
                if pe[u] == -1:
                    pull[u] += g.w[e]
                    heapq.heappush(queue, (-int(pull[u]), int(u)))
        pe[pe == -2] = -1
        left -= load
        cursor = 0
    load = np.bincount(pe[pe >= 0], weights=g.c[pe >= 0], minlength=k).astype(np.int64)
    for v in np.flatnonzero(pe < 0):
        t = int((bound - load).argmax())
        pe[v] = t
        load[t] += g.c[v]
    return pe


def partition(g: Small, bound: np.ndarray, config: Config) -> np.ndarray:
    """Edge-cut multilevel partition into len(bound) blocks, with the relaxed filter that suits edge-cut."""
    k = len(bound)
    config = config.but(filter_mode="relaxed")
    if k == 1:
        return np.zeros(g.n, np.int64)
    flat = np.ones((k, k)) - np.eye(k)
    if config.initial == "bisect" and k > 2:
        return bisection(g, bound, config)
    return multilevel(g, flat, bound, config, lambda small, c: refine(small, grow(small, bound, c), flat, bound, c))


def bisection(g: Small, bound: np.ndarray, config: Config) -> np.ndarray:
    """Recursive bisection: halves of the blocks share the bounds of their members."""
    k = len(bound)
    if k == 1:
        return np.zeros(g.n, np.int64)
    half = k // 2
    two = np.array([bound[:half].sum(), bound[half:].sum()])
    side = partition(g, two, config.but(initial="direct"))
    pe = np.empty(g.n, np.int64)
    for s, (own, base) in enumerate(((bound[:half], 0), (bound[half:], half))):
        inner, at = g.within(side == s)
        pe[at] = base + bisection(inner, own, config)
    return pe


def multilevel(g: Small, dist: np.ndarray, bound: np.ndarray, config: Config, initial, spent: dict[str, float] | None = None) -> np.ndarray:
    """Coarsen, map the coarsest graph, and refine on the way back. spent gets the CPU seconds of each phase."""
    spent = {} if spent is None else spent

    def timed(phase: str, run, *args):
        began = time.process_time()
        got = run(*args)
        spent[phase] = spent.get(phase, 0.0) + time.process_time() - began
        return got

    levels = []
    now = g
    while now.n >= config.coarsest_factor * len(bound) and len(levels) < config.levels:
        for method in dict.fromkeys((config.coarsening, "cluster")):
            if method == "matching":
                coarse = timed("coarsen", matching, now, int(bound.max()), config)
            else:
                coarse = timed("coarsen", clustering, now, max(2, int(bound.max()) // config.cluster_share), config)
            small = timed("contract", now.contract, coarse)
            if shrunk := small.n <= (1 - config.least_shrink) * now.n:
                break
        if not shrunk:
            break
        levels.append((now, coarse))
        now = small
    starts = []
    for r in range(max(1, config.restarts)):
        pe = timed("initial", initial, now, config.but(seed=config.seed + r))
        pe = timed("refine", improve, now, pe, dist, bound, config)
        load = np.bincount(pe, weights=now.c, minlength=len(bound))
        starts.append((max(0, int((load - bound).max())), objective(now, pe, dist), r, pe))
    pe = min(starts, key=lambda x: x[:3])[3]
    for fine, coarse in reversed(levels):
        pe = timed("uncontract", pe.__getitem__, coarse)
        pe = timed("refine", improve, fine, pe, dist, bound, config)
    return pe


def adaptive_eps(total: int, part: int, k: int, k_part: int, eps: float, levels_left: int) -> float:
    """The imbalance that a split may have so that all splits below it together stay within eps.

    The part's slack is what it may weigh over what it weighs; each of the levels left takes an equal root of it.
    """
    slack = (1 + eps) * k_part * total / (k * part) if part else 1 + eps
    return max(0.0, slack ** (1 / levels_left) - 1)


def inner_bound(part: int, arity: int, eps: float, leaf: int | None) -> int:
    """The bound of a split's blocks: rounded down, so that rounding takes no slack; at the leaves the global bound."""
    least = -(-part // arity)
    return max(least, int((1 + eps) * part / arity + 1e-9)) if leaf is None else max(leaf, least)


def multisection(g: Small, topology: Topology, config: Config, total: int | None = None) -> np.ndarray:
    """Split along the tree, level by level; the PE is the path of choices."""
    eps = config.eps_num / config.eps_den
    total = int(g.c.sum()) if total is None else total
    k = topology.k
    leaf = load_bound(total, k, config.eps_num, config.eps_den)
    pe = np.zeros(g.n, np.int64)
    parts = [(g, np.arange(g.n))]
    below = k
    for level in range(len(topology.arity), 0, -1):
        arity = topology.arity[level - 1]
        next_parts = []
        below //= arity
        for own, at in parts:
            weight = int(own.c.sum())
            part_eps = adaptive_eps(total, weight, k, below * arity, eps, level) if config.adaptive else eps
            limit = leaf if level == 1 and config.adaptive else None
            bound = np.full(arity, inner_bound(weight, arity, part_eps, limit))
            side = partition(own, bound, config)
            pe[at] += side * below
            if level > 1:
                for s in range(arity):
                    inner, where = own.within(side == s)
                    next_parts.append((inner, at[where]))
        parts = next_parts
    return pe


def integrated(g: Small, topology: Topology, config: Config, total: int | None = None, spent: dict[str, float] | None = None) -> np.ndarray:
    """The multilevel mapper on the communication cost, with multisection for the coarsest graph."""
    total = int(g.c.sum()) if total is None else total
    bound = np.full(topology.k, load_bound(total, topology.k, config.eps_num, config.eps_den))
    start = lambda small, c: multisection(small, topology, c.but(passes=1), total)
    return multilevel(g, topology.dense(), bound, config, start, spent)


def sequential_lp(g: Small, pe: np.ndarray, dist: np.ndarray, bound: np.ndarray, config: Config, rounds: int = 10) -> np.ndarray:
    """Classic label propagation: one vertex after another in a seeded order, only feasible moves that improve, at once."""
    k = len(bound)
    load = np.bincount(pe, weights=g.c, minlength=k).astype(np.int64).tolist()
    rows = g.rows()
    order = np.argsort(edge_noise_array(np.arange(g.n), np.arange(g.n), config.seed), kind="stable").tolist()
    # how many edges of each vertex lead to other blocks: where none does, there is no move to try
    away = np.bincount(g.src[pe[g.src] != pe[g.dst]], minlength=g.n).tolist()
    at, c, most, d = pe.tolist(), g.c.tolist(), bound.tolist(), dist.tolist()
    edges: dict[int, tuple[list[int], list[int]]] = {}
    for _ in range(rounds):
        moved = 0
        for v in order:
            if not away[v]:
                continue
            if v not in edges:
                e = slice(rows[v], rows[v + 1])
                edges[v] = g.dst[e].tolist(), g.w[e].tolist()
            near, own, volume = edges[v][0], at[v], {}
            for u, w in zip(*edges[v]):
                volume[at[u]] = volume.get(at[u], 0) + w
            here = sum([w * d[own][x] for x, w in volume.items()])
            best, to = 0, -1
            for b in sorted(volume):
                if b != own and load[b] + c[v] <= most[b]:
                    gain = here - sum([w * d[b][x] for x, w in volume.items()])
                    if gain > best:
                        best, to = gain, b
            if to >= 0:
                load[own] -= c[v]
                load[to] += c[v]
                at[v] = to
                for u in near:
                    away[u] += (at[u] == own) - (at[u] == to)
                away[v] = sum([at[u] != to for u in near])
                moved += 1
        if not moved:
            break
    return np.array(at, np.int64)


def place_blocks(volume: np.ndarray, dist: np.ndarray, rounds: int = 50) -> np.ndarray:
    """One block for each PE: greedy by volume, then pairwise swaps while one helps. The PE of each block."""
    k = len(volume)
    volume = volume + 0.0
    pe = np.full(k, -1, np.int64)
    free = np.ones(k, bool)
    into = np.zeros(k)
    for step in range(k):
        open_ = pe < 0
        b = int(np.where(open_, into if step else volume.sum(1), -1).argmax())
        placed = np.flatnonzero(~open_)
        cost = dist[:, pe[placed]] @ volume[b, placed] if len(placed) else np.zeros(k)
        t = int(np.where(free, cost, np.inf).argmin())
        pe[b], free[t] = t, False
        into += volume[b]
    for _ in range(rounds):
        changed = False
        for a in range(k):
            d = dist[np.ix_(pe, pe)]
            # the change of the (undirected) cost when a and b change places
            now = (volume * d).sum(1)
            swap = volume @ d[:, a] - volume[:, a] * d[:, a]
            other = d @ volume[a] - d[:, a] * volume[a, a]
            delta = swap + other - now[a] - now + 2 * volume[a] * d[a]
            b = int(delta.argmin())
            if delta[b] < -1e-9:
                pe[a], pe[b] = pe[b], pe[a]
                changed = True
        if not changed:
            break
    return pe


def exact(g: Small, k: int, dist: np.ndarray, bound: np.ndarray) -> tuple[int, np.ndarray | None]:
    """Brute force over all mappings within the bounds, for a handful of vertices."""
    if k**g.n > 1 << 26:
        raise ValueError("too many mappings to try")
    best, found = None, None
    pe = np.zeros(g.n, np.int64)

    def walk(v: int, load: np.ndarray) -> None:
        nonlocal best, found
        if v == g.n:
            j = objective(g, pe, dist)
            if best is None or j < best:
                best, found = j, pe.copy()
            return
        for b in range(k):
            if load[b] + g.c[v] <= bound[b]:
                pe[v] = b
                load[b] += g.c[v]
                walk(v + 1, load)
                load[b] -= g.c[v]

    walk(0, np.zeros(k, np.int64))
    return (-1 if best is None else best), found
