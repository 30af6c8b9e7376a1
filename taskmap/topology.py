"""The machine: a regular tree of processing elements (PEs), or any symmetric matrix of cost factors.

In a tree with arities a_1:...:a_l the component of PE x at level i is x div (a_1 ... a_i). The cost factor of two PEs is 0
if they are one, else d_i for the lowest level i where they share a component. This is a closed form, so no table of PE
pairs is needed; a Column expression stays inside generated code.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from functools import reduce
from itertools import accumulate
from operator import mul

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _column(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def floor_div(x: Column | str, n: int) -> Column:
    """Integer division of a non-negative column."""
    return F.call_function("div", _column(x), F.lit(n)).cast("int") if n > 1 else _column(x).cast("int")


@dataclass(frozen=True)
class Topology:
    arity: tuple[int, ...]
    distances: tuple[int, ...]

    def __post_init__(self) -> None:
        if len(self.arity) != len(self.distances) or not self.arity:
            raise ValueError("as many arities as distances are needed, and at least one")
        if min(self.arity) < 1 or min(self.distances) < 0:
            raise ValueError("arities must be positive and distances not negative")

    @classmethod
    def parse(cls, hierarchy: str, distance: str) -> Topology:
        return cls(tuple(map(int, hierarchy.split(":"))), tuple(map(int, distance.split(":"))))

    @classmethod
    def flat(cls, k: int) -> Topology:
        """All distances 1: the communication cost is twice the edge-cut."""
        return cls((k,), (1,))

    @classmethod
    def from_json(cls, text: str) -> Topology:
        told = json.loads(text)
        return cls(tuple(told["hierarchy"]), tuple(told["distance"]))

    def to_json(self) -> str:
        return json.dumps({"hierarchy": list(self.arity), "distance": list(self.distances)})

    @property
    def k(self) -> int:
        return reduce(mul, self.arity, 1)

    @property
    def sizes(self) -> tuple[int, ...]:
        """PEs of a component at each level, from the lowest."""
        return tuple(accumulate(self.arity, mul))

    def __str__(self) -> str:
        return ":".join(map(str, self.arity))

    def component(self, pe: Column | str, level: int) -> Column:
        """The component of a PE at a level (1 is the lowest)."""
        return floor_div(pe, self.sizes[level - 1])

    def coords(self, pe: Column | str) -> Column:
        return F.array(*[self.component(pe, i + 1) for i in range(len(self.arity))])

    def level(self, x: Column | str, y: Column | str) -> Column:
        """The lowest level at which two PEs share a component, 0 for one PE."""
        out = F.when(_column(x) == _column(y), F.lit(0))
        for i in range(1, len(self.arity)):
            out = out.when(self.component(x, i) == self.component(y, i), F.lit(i))
        return out.otherwise(F.lit(len(self.arity)))

    def distance(self, x: Column | str, y: Column | str) -> Column:
        out = F.when(_column(x) == _column(y), F.lit(0))
        for i in range(1, len(self.arity)):
            out = out.when(self.component(x, i) == self.component(y, i), F.lit(self.distances[i - 1]))
        return out.otherwise(F.lit(self.distances[-1])).cast("long")

    def distance_sql(self, x: str, y: str) -> str:
        """The same as SQL text that Spark (div) understands."""
        arms = [f"WHEN {x} = {y} THEN 0"]
        arms += [f"WHEN {x} div {n} = {y} div {n} THEN {d}" for n, d in zip(self.sizes[:-1], self.distances)]
        return f"CASE {' '.join(arms)} ELSE {self.distances[-1]} END"

    def pes(self, spark: SparkSession) -> DataFrame:
        return spark.range(self.k).select(F.col("id").cast("int").alias("pe"))

    def matrix(self, spark: SparkSession) -> DataFrame:
        """pe_x, pe_y, d for all pairs: k squared rows, made from one range without a join."""
        both = spark.range(self.k * self.k)
        x, y = F.floor(F.col("id") / self.k).cast("int"), (F.col("id") % self.k).cast("int")
        return both.select(x.alias("pe_x"), y.alias("pe_y")).withColumn("d", self.distance("pe_x", "pe_y"))

    def dense(self) -> np.ndarray:
        """The matrix as an array, for kernels."""
        pe = np.arange(self.k)
        out = np.full((self.k, self.k), self.distances[-1], np.int64)
        for n, d in reversed(list(zip(self.sizes[:-1], self.distances[:-1]))):
            out[(pe[:, None] // n) == (pe[None, :] // n)] = d
        np.fill_diagonal(out, 0)
        return out

    def inner(self, level: int) -> Topology:
        """The tree below a component of that level (1: a single processor's PEs)."""
        return Topology(self.arity[:level], self.distances[:level])


#: PEs of a general cost matrix, at most: its rows are broadcast to the joins that look costs up.
MOST_MATRIX_PES = 2048


@dataclass(frozen=True)
class MatrixTopology:
    """The general problem: an explicit symmetric matrix pe_x, pe_y, d that reaches every pair."""

    rows: DataFrame
    k: int

    @classmethod
    def of(cls, rows: DataFrame) -> MatrixTopology:
        told = rows.agg(F.count("*").alias("n"), F.max("pe_x").alias("top")).head()
        k = (told["top"] or 0) + 1
        if k > MOST_MATRIX_PES:
            raise ValueError(f"a cost matrix is broadcast and may have {MOST_MATRIX_PES} PEs at most, not {k}")
        if told["n"] != k * k:
            raise ValueError("every pair of PEs needs a cost factor")
        mirrored = rows.alias("a").join(F.broadcast(rows).alias("b"), (F.col("a.pe_x") == F.col("b.pe_y")) & (F.col("a.pe_y") == F.col("b.pe_x")))
        if mirrored.filter("a.d <> b.d").limit(1).count():
            raise ValueError("the cost matrix must be symmetric")
        return cls(rows, k)

    def lookup(self, df: DataFrame, x: str, y: str, name: str = "d") -> DataFrame:
        """df with the cost factor of the PEs in columns x and y."""
        costs = self.rows.select(F.col("pe_x").alias(x), F.col("pe_y").alias(y), F.col("d").cast("long").alias(name))
        return df.join(F.broadcast(costs), [x, y])

    def dense(self) -> np.ndarray:
        out = np.zeros((self.k, self.k), np.int64)
        for r in self.rows.collect():
            out[r["pe_x"], r["pe_y"]] = r["d"]
        return out


def with_distance(df: DataFrame, topology: Topology | MatrixTopology, x: str, y: str, name: str = "d") -> DataFrame:
    if isinstance(topology, MatrixTopology):
        return topology.lookup(df, x, y, name)
    return df.withColumn(name, topology.distance(x, y))


def from_nation(nation: DataFrame, region: DataFrame) -> DataFrame:
    """pe, nation, region, l1, l2: nations as PEs, regions as the components above them.

    PEs are numbered by region and nation. Both tables are of fixed size in this schema.
    """
    from pyspark.sql import Window as W

    order = F.row_number().over(W.orderBy("n_regionkey", "n_nationkey")) - 1
    both = nation.join(F.broadcast(region), nation["n_regionkey"] == region["r_regionkey"])
    own = both.select(order.cast("int").alias("pe"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"), F.col("n_regionkey").cast("int").alias("l1"))
    return own.withColumn("l2", F.lit(0))


def load_bound(total: int, k: int, eps_num: int, eps_den: int) -> int:
    """The largest weight a block may have: the ceiling of (1 + eps) times the average, in integers."""
    return ((eps_den + eps_num) * total + eps_den * k - 1) // (eps_den * k)


def load_bound_column(total: Column, k: Column, eps_num: int, eps_den: int) -> Column:
    """The same as an expression; div on longs stays exact."""
    return F.call_function("div", F.lit(eps_den + eps_num) * total + F.lit(eps_den) * k - F.lit(1), F.lit(eps_den) * k)
