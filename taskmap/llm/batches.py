"""Packed exchanges between batches of documents and shards of a hash space.

Several operators ask of every window or sketch of a corpus whether it occurs elsewhere. As rows these would be tens of
billions; here a batch of documents (by a hash of the id) sends each shard one row with a packed array, and each shard
answers each batch with one row. A batch sends what it holds several times only once, so a text that a third of all
documents share reaches a shard once for each batch, not once for each document.

Batches grow with the root of the input, up to BATCH_MB, so that packed rows neither become tiny nor outgrow a task.
The documents' own exchange is written once and read again by each later step of the same query.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmap.llm.common import NULL_ID, U64, batch_of, size_estimate, texts

LEAST_MB, BATCH_MB = 3.0, 256.0


def batch_mb(total: int) -> float:
    """Megabytes of files for a batch."""
    return max(LEAST_MB, min(BATCH_MB, 0.13 * math.sqrt(total / 1e6)))


def counted(docs: DataFrame) -> tuple[int, int]:
    """The number of batches, and the bits of a shard's number: as many shards as batches, about."""
    total = size_estimate(docs)
    width = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n = max(2 * width, math.ceil(total / 1e6 / batch_mb(total)))
    return n, max(1, math.ceil(math.log2(n)))


def batched(docs: DataFrame, n: int, carry: bool = False) -> DataFrame:
    """batch, doc_id, text; null ids as NULL_ID, null texts empty. With carry, all columns besides as a struct, row."""
    own = texts(docs, *([F.struct(*[F.col(c) for c in docs.columns if c != "text"]).alias("row")] if carry else []))
    return own.select(batch_of(F.col("doc_id"), n).alias("batch"), F.coalesce("doc_id", F.lit(NULL_ID)).alias("doc_id"), *own.columns[1:])


def in_order(table: pa.Table) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """A batch's ids and texts by (id, text), and that order: equal ids always meet in one batch, so it is the corpus's."""
    ids = table.column("doc_id").to_numpy()
    raw = table.column("text").combine_chunks().cast(pa.large_binary()).to_pylist()
    order = np.argsort(ids, kind="stable")
    if len(ids) > 1 and (np.diff(ids[order]) == 0).any():
        order = np.array(sorted(range(len(ids)), key=lambda i: (ids[i], raw[i])))
    return ids[order], [raw[i] for i in order], order


def shard_bounds(values: np.ndarray, bits: int) -> np.ndarray:
    """Where each shard begins in sorted uint64 values, by their highest bits; one more entry ends the last."""
    edges = np.arange(1 << bits, dtype=U64) << U64(64 - bits)
    return np.append(np.searchsorted(values, edges), len(values))


def packed(columns: list[np.ndarray], bounds: np.ndarray, batch: int, names: list[str]) -> pa.Table:
    """A row for each shard that gets anything: shard, batch and the arrays' bytes."""
    shards = np.flatnonzero(np.diff(bounds))
    cut = [[c[bounds[s] : bounds[s + 1]].tobytes() for s in shards] for c in columns]
    own = [pa.array(shards.astype(np.int32)), pa.array(np.full(len(shards), batch, np.int32)), *[pa.array(c, pa.binary()) for c in cut]]
    return pa.table(own, ["shard", "batch", *names])


def unpacked(table: pa.Table, name: str, dtype: str) -> tuple[np.ndarray, np.ndarray]:
    """All rows' arrays, joined, and the length of each."""
    parts = [np.frombuffer(x, dtype) for x in table.column(name).to_pylist()]
    return (np.concatenate(parts) if parts else np.zeros(0, dtype)), np.array([len(p) for p in parts], np.int64)


def answers(table: pa.Table, flags: np.ndarray, sizes: np.ndarray) -> pa.Table:
    """A row for each row of a shard's input: batch, shard and its share of flags, in the order sent."""
    ends = np.cumsum(sizes)
    cut = [flags[e - n : e].tobytes() for e, n in zip(ends, sizes)]
    return pa.table([table.column("batch"), table.column("shard"), pa.array(cut, pa.binary())], ["batch", "shard", "flags"])


def joined(table: pa.Table, dtype: str = "u1") -> np.ndarray:
    """What all shards answered to a batch, in the order of its own sorted values."""
    shards = table.column("shard").to_numpy()
    rows = table.column("flags").to_pylist()
    parts = [np.frombuffer(rows[i], dtype) for i in np.argsort(shards, kind="stable")]
    return np.concatenate(parts) if parts else np.zeros(0, dtype)


class WordHashes(dict):
    """64-bit hashes of words, computed once each; starts anew when full."""

    LIMIT = 200_000

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= self.LIMIT:
            self.clear()
        got = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 64:
            self[word] = got
        return got

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), U64, len(words))
