"""Approximate nearest neighbours from low-dimensional stable projections.

Gaussian projections keep Euclidean distances in distribution: the squared projected distance of two points, over their
squared distance, is chi-square with as many degrees of freedom as there are projections. A kd-tree over the projected
points therefore yields them by projected distance, and each is verified with the original vectors. Once the next
projected distance, compared with the current k-th distance, is one that a nearer point would show with probability
below 1 - CONFIDENCE, the search stops: the chi-square stopping test.

On a cluster the projected space falls into cells, by a coarse kd-tree over a bounded sample of points (SAMPLE, whatever
the size of the table). Every row goes to its cell and is indexed there. A query is first answered in its own cell; the
k-th distance found bounds the projected radius by the same test, and only cells within that radius are asked in a second
round. Queries and rows meet cell by cell; cells have about CELL rows, so memory is bounded however many there are.

Defined results: vectors that are null, empty or zero, or hold nulls or non-finite numbers, take no part, nor do those
whose length isn't the most frequent one; queries with equal ids are answered once, for the vector that comes first by
its components; rows with a query's id are not its candidates; null ids take no part; with fewer than k candidates all
are returned; ties go to the smaller id.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.llm.common import table

DIMENSIONS = 8
CONFIDENCE = 0.985
LEAF = 64
#: Rows of a cell, about; rows from which the cells are drawn, at most.
CELL, SAMPLE = 20_000, 20_000
SEED = 20_011


def chi_square_cdf(x: float, k: int) -> float:
    """The regularised lower incomplete gamma function at (k / 2, x / 2), by its power series."""
    if x <= 0:
        return 0.0
    a, half = k / 2, x / 2
    term = total = 1 / a
    n = a
    while term > total * 1e-15:
        n += 1
        term *= half / n
        total += term
    return min(1.0, total * math.exp(-half + a * math.log(half) - math.lgamma(a)))


def chi_square_quantile(p: float, k: int) -> float:
    low, high = 0.0, 10.0 * k + 100
    for _ in range(200):
        middle = (low + high) / 2
        low, high = (middle, high) if chi_square_cdf(middle, k) < p else (low, middle)
    return high


def projection(width: int) -> np.ndarray:
    return np.random.default_rng(SEED).standard_normal((width, DIMENSIONS))


class KdTree:
    """Boxes over the projected points, in arrays; leaves hold up to LEAF points."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.points, self.order = points, np.arange(len(points))
        self.nodes: list[tuple[np.ndarray, np.ndarray, int, int, int, int]] = []
        if len(points):
            self._build(0, len(points), leaf)

    def _build(self, start: int, end: int, leaf: int) -> int:
        """Splits at the median of the widest side; works off a stack, so depth is no limit."""
        root = len(self.nodes)
        self.nodes.append(None)
        stack = [(root, start, end)]
        while stack:
            at, a, b = stack.pop()
            own = self.points[self.order[a:b]]
            low, high = own.min(0), own.max(0)
            side = int(np.argmax(high - low))
            if b - a <= leaf or high[side] == low[side]:
                self.nodes[at] = (low, high, a, b, -1, -1)
                continue
            half = (b - a) // 2
            self.order[a:b] = self.order[a:b][np.argpartition(own[:, side], half)]
            left, right = len(self.nodes), len(self.nodes) + 1
            self.nodes += [None, None]
            self.nodes[at] = (low, high, a, b, left, right)
            stack += [(left, a, a + half), (right, a + half, b)]
        return root

    @staticmethod
    def gap(low: np.ndarray, high: np.ndarray, q: np.ndarray) -> float:
        """The squared distance of a point from a box."""
        d = np.maximum(np.maximum(low - q, q - high), 0)
        return float(d @ d)

    def leaves(self, q: np.ndarray):
        """Yields (squared gap, rows) of leaves by growing gap: no row of a later leaf is nearer than its gap."""
        if not self.nodes:
            return
        queue = [(self.gap(*self.nodes[0][:2], q), 0)]
        while queue:
            gap, at = heapq.heappop(queue)
            low, high, a, b, left, right = self.nodes[at]
            if left < 0:
                yield gap, self.order[a:b]
                continue
            for child in (left, right):
                heapq.heappush(queue, (self.gap(*self.nodes[child][:2], q), child))


@dataclass
class Index:
    ids: np.ndarray
    vectors: np.ndarray
    tree: KdTree

    @classmethod
    def build(cls, ids: np.ndarray, vectors: np.ndarray, matrix: np.ndarray) -> Index:
        vectors = vectors.astype(np.float64)
        return cls(ids, vectors, KdTree(vectors @ matrix))

    def search(self, own: int, vector: np.ndarray, projected: np.ndarray, k: int, stop: float, bound: float = math.inf) -> list[tuple[float, int]]:
        """Up to k (distance, id), nearest first; what is farther than bound need not be found."""
        best: list[tuple[float, int]] = []
        limit = bound
        for gap, rows in self.tree.leaves(projected):
            if gap > limit * limit * stop:
                break  # the chi-square test: nearer points would very likely project nearer than this
            near = self.tree.points[rows] - projected
            rows = rows[np.einsum("ij,ij->i", near, near) <= limit * limit * stop]
            rows = rows[self.ids[rows] != own]
            if not len(rows):
                continue
            apart = self.vectors[rows] - vector
            found = np.sqrt(np.einsum("ij,ij->i", apart, apart))
            good = found <= limit
            if good.any():
                best = sorted(best + list(zip(found[good].tolist(), self.ids[rows[good]].tolist())))[:k]
                if len(best) == k:
                    limit = min(limit, best[-1][0])
        return best


@dataclass
class Cells:
    """A coarse kd-tree: splits as (side, value, left, right), cells as negative numbers, boxes that cover all space."""

    splits: list[tuple[int, float, int, int]]
    low: np.ndarray
    high: np.ndarray

    @classmethod
    def build(cls, points: np.ndarray, cells: int) -> Cells:
        splits: list = []
        lows, highs = [], []

        def make(own: np.ndarray, n: int, low: np.ndarray, high: np.ndarray) -> int:
            side = int(np.argmax(own.max(0) - own.min(0))) if len(own) else 0
            value = float(np.median(own[:, side])) if len(own) else 0.0
            if n <= 1 or len(own) < 2 or not (own[:, side] <= value).any() or (own[:, side] <= value).all():
                lows.append(low), highs.append(high)
                return -len(lows)
            at = len(splits)
            splits.append(None)
            middle_low, middle_high = low.copy(), high.copy()
            middle_high[side] = middle_low[side] = value
            left = make(own[own[:, side] <= value], n // 2, low, middle_high)
            right = make(own[own[:, side] > value], n - n // 2, middle_low, high)
            splits[at] = (side, value, left, right)
            return at

        make(points, cells, np.full(DIMENSIONS, -np.inf), np.full(DIMENSIONS, np.inf))
        return cls(splits, np.array(lows), np.array(highs))

    def of(self, points: np.ndarray) -> np.ndarray:
        cell = np.zeros(len(points), np.int32)
        stack = [(0, np.arange(len(points)))] if self.splits else []
        while stack:
            at, rows = stack.pop()
            side, value, left, right = self.splits[at]
            below = points[rows, side] <= value
            for child, some in ((left, rows[below]), (right, rows[~below])):
                if child < 0:
                    cell[some] = -child - 1
                elif len(some):
                    stack.append((child, some))
        return cell

    def within(self, point: np.ndarray, radius: float) -> np.ndarray:
        d = np.maximum(np.maximum(self.low - point, point - self.high), 0)
        return np.flatnonzero((d * d).sum(1) <= radius * radius)


FOUND = "query_id long, vec_id long, score double, vector array<double>"


def _matrix(table: pa.Table, name: str) -> np.ndarray:
    rows = table.column(name).combine_chunks()
    return rows.values.to_numpy(zero_copy_only=False).reshape(len(rows), -1).astype(np.float64) if len(rows) else np.zeros((0, 1))


def valid_vectors(vectors: DataFrame, id_name: str, vector_name: str) -> DataFrame:
    """vec_id and vector array<double> of the rows that take part."""
    v = F.col(vector_name)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != F.lit(math.inf))) & F.exists(v, lambda x: x != 0)
    return vectors.filter(F.col(id_name).isNotNull() & v.isNotNull() & fine).select(F.col(id_name).cast("long").alias("vec_id"), v.cast("array<double>").alias("vector"))


def nearest(vectors: DataFrame, queries: Column, k: int = 10, id_name: str = "vec_id", vector_name: str = "embedding", confidence: float = CONFIDENCE) -> DataFrame:
    """query_id, rank, vec_id, score for the rows for which queries (a condition on vec_id) holds, against all rows."""
    rows = valid_vectors(vectors, id_name, vector_name)
    widths = rows.groupBy(F.size("vector").alias("width")).count().orderBy(F.desc("count"), "width").limit(1).collect()
    width, n = (widths[0]["width"], widths[0]["count"]) if widths else (1, 0)
    rows = rows.filter(F.size("vector") == width)
    matrix, stop = projection(width), chi_square_quantile(confidence, DIMENSIONS)
    # of equal vectors only those with the k + 1 least ids can be among anyone's k nearest, so a very common one stays small
    least = F.dense_rank().over(W.partitionBy("vector").orderBy("vec_id"))
    standing = rows.withColumn("least", least).filter(F.col("least") <= k + 1).drop("least")
    sample = standing.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("vector").collect() if n > CELL else []
    points = np.array([r["vector"] for r in sample]).reshape(-1, width) @ matrix
    cells = Cells.build(points, math.ceil(n / CELL))

    def place(batches):
        for batch in batches:
            t = pa.Table.from_batches([batch])
            yield pa.RecordBatch.from_arrays([pa.array(cells.of(_matrix(t, "vector") @ matrix), pa.int32()), batch.column("vec_id"), batch.column("vector")], ["cell", "vec_id", "vector"])

    placed = standing.mapInArrow(place, "cell int, vec_id long, vector array<double>")
    # the smallest vector stands for queries with equal ids
    asked = rows.filter(queries).groupBy("vec_id").agg(F.min("vector").alias("vector"))
    asked = asked.mapInArrow(place, "cell int, vec_id long, vector array<double>").select("cell", "vec_id", "vector", F.lit(math.inf).alias("bound"))

    def answer(ours: pa.Table, theirs: pa.Table) -> pa.Table:
        out: tuple[list, list, list, list] = ([], [], [], [])
        if len(theirs):
            index = Index.build(ours.column("vec_id").to_numpy(), _matrix(ours, "vector") if len(ours) else np.zeros((0, width)), matrix)
            v = _matrix(theirs, "vector")
            for own, vector, projected, bound in zip(theirs.column("vec_id").to_pylist(), v, v @ matrix, theirs.column("bound").to_pylist()):
                got = index.search(own, vector, projected, k, stop, bound)
                first = bound == math.inf
                if first and len(got) < k:
                    got = [*got, *[(math.inf, None)] * (k - len(got))]  # the other cells are asked without a bound
                for score, vec_id in got:
                    for column, value in zip(out, (own, vec_id, score, None)):
                        column.append(value)
                if first and got:
                    out[3][-1] = vector.tolist()  # travels on with the k-th distance
        return pa.table([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int64(), pa.float64(), pa.list_(pa.float64())))], ["query_id", "vec_id", "score", "vector"])

    home = placed.groupBy("cell").cogroup(asked.groupBy("cell")).applyInArrow(answer, FOUND)
    if len(cells.low) > 1:
        from taskmap.llm.common import ensure_checkpoints

        ensure_checkpoints(vectors.sparkSession)
        home = home.checkpoint()

        def spread(batches):
            for batch in batches:
                rows = batch.to_pylist()
                out = [[], [], [], []]
                for r in rows:
                    point = np.array(r["vector"])
                    projected = point @ matrix
                    own = cells.of(projected[None])[0]
                    for cell in cells.within(projected, r["score"] * math.sqrt(stop)):
                        if cell != own:
                            for column, value in zip(out, (int(cell), r["query_id"], r["vector"], r["score"])):
                                column.append(value)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int32(), pa.int64(), pa.list_(pa.float64()), pa.float64()))], ["cell", "vec_id", "vector", "bound"])

        # a bound of infinity here means that the own cell had fewer than k rows: the largest finite number asks for all
        again = home.filter(F.col("vector").isNotNull()).withColumn("score", F.least("score", F.lit(1e150))).mapInArrow(spread, "cell int, vec_id long, vector array<double>, bound double")
        home = home.unionByName(placed.groupBy("cell").cogroup(again.groupBy("cell")).applyInArrow(answer, FOUND))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy("score", "vec_id")).cast("int")
    return home.filter(F.col("vec_id").isNotNull()).withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op8_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op8_neighbours": op8_neighbours}
SQL: dict[str, str] = {}
