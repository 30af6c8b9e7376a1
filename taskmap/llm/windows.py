"""Substring dedup by Rabin-Karp hashes of every fixed-length window of words.

Each document is a sequence of words; each window of LENGTH consecutive words has a polynomial hash, rolled over the
words' own hashes in two bases (128 bits). A window that also starts in a document with a smaller id is repeated, and
repeated windows of a document merge into maximal intervals of words, which are removed.

Counting goes in two steps. First every distinct window hash of a batch of documents goes to its shard, packed, as 32
bits besides the shard's number; a shard says which of them occur in several batches or several times. This is only a
filter: it errs towards keeping. Then those that remain go with all 128 bits and the smallest id of the batch, and shards
answer with the hashes that occur under a smaller id elsewhere. What a batch holds several times is settled within it.

Defined results: null and empty texts have no words; windows are judged on the input, not on what is left; rows with equal
ids are not each other's predecessors; null ids come before all others.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from taskmap.llm.batches import WordHashes, answers, batched, counted, in_order, joined, packed, shard_bounds, unpacked
from taskmap.llm.common import U64, documents, mixed, null_ids, relieved

LENGTH = 13
BASES = (U64(0x9E3779B97F4A7C55), U64(0xC2B2AE3D27D4EB4F))


def rolled(words: np.ndarray, length: int, base: np.uint64) -> np.ndarray:
    """Polynomial hashes of all windows, by Horner's rule over shifted views; scrambled so that all bits are used."""
    n = len(words) - length + 1
    if n <= 0:
        return np.zeros(0, U64)
    h = words[:n].copy()
    for i in range(1, length):
        h *= base
        h += words[i : i + n]
    return mixed(h)


def merged(starts: np.ndarray, length: int, n: int) -> np.ndarray:
    """The positions, of n, that windows of that length at these starts cover, as booleans."""
    steps = np.zeros(n + 1, np.int32)
    np.add.at(steps, starts, 1)
    np.add.at(steps, starts + length, -1)
    return np.cumsum(steps[:n]) > 0


_hashes = WordHashes()


class Batch:
    """The windows of a batch: hashes in both bases, and for each the number of its document."""

    def __init__(self, table: pa.Table, length: int):
        self.ids, self.raw, _ = in_order(table)
        self.words = [r.split() for r in self.raw]
        hashed = [_hashes.of(w) for w in self.words]
        first = [rolled(h, length, BASES[0]) for h in hashed]
        self.sizes = np.array([len(f) for f in first], np.int64)
        self.doc = np.repeat(np.arange(len(first)), self.sizes)
        self.first = np.concatenate(first) if first else np.zeros(0, U64)
        self.second = lambda: np.concatenate([rolled(h, length, BASES[1]) for h in hashed])
        self.order = np.argsort(self.first, kind="stable")  # within a hash by document, as ids ascend
        ordered = self.first[self.order]
        self.starts = np.flatnonzero(np.append(True, ordered[1:] != ordered[:-1])) if len(ordered) else np.zeros(0, np.int64)
        self.distinct = ordered[self.starts]

    def group(self) -> np.ndarray:
        """The number of each window's hash among the distinct ones."""
        own = np.zeros(len(self.order), np.int64)
        own[self.order] = np.repeat(np.arange(len(self.starts)), np.diff(np.append(self.starts, len(self.order))))
        return own


def repeated_words(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_words, n_removed, intervals (array of start, end in words, end excluded), kept (the remaining words)."""
    n, bits = counted(docs)
    rows = batched(docs, n)

    def short(values: np.ndarray) -> np.ndarray:
        return ((values >> U64(32 - bits)) & U64(0xFFFFFFFF)).astype(np.uint32)

    def send_all(table: pa.Table) -> pa.Table:
        own = Batch(table, length)
        return packed([short(own.distinct)], shard_bounds(own.distinct, bits), table.column("batch")[0].as_py(), ["hashes"])

    def count(table: pa.Table) -> pa.Table:
        values, sizes = unpacked(table, "hashes", "u4")
        order = np.argsort(values, kind="stable")
        ordered = values[order]
        same = ordered[1:] == ordered[:-1]
        often = np.zeros(len(values), np.uint8)
        often[order] = np.append(same, False) | np.append(False, same)
        return answers(table, often, sizes)

    def send_often(table: pa.Table, told: pa.Table) -> pa.Table:
        names = ["hashes", "others", "ids"]
        if not len(table):
            return packed([], np.zeros(1, np.int64), 0, [])
        own = Batch(table, length)
        often = joined(told).astype(bool)
        if not often.any():
            return pa.table([pa.array([], t) for t in (pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary())], ["shard", "batch", *names])
        at = own.order[own.starts[often]]
        values = own.distinct[often]
        return packed([values, own.second()[at], own.ids[own.doc[at]]], shard_bounds(values, bits), table.column("batch")[0].as_py(), names)

    def judge(table: pa.Table) -> pa.Table:
        values, sizes = unpacked(table, "hashes", "u8")
        others, ids = unpacked(table, "others", "u8")[0], unpacked(table, "ids", "i8")[0]
        order = np.lexsort((ids, others, values))
        v, o = values[order], others[order]
        fresh = np.append(True, (v[1:] != v[:-1]) | (o[1:] != o[:-1])) if len(v) else np.zeros(0, bool)
        least = ids[order][np.maximum.accumulate(np.where(fresh, np.arange(len(v)), 0))]
        later = np.zeros(len(values), bool)
        later[order] = ids[order] > least
        ends = np.cumsum(sizes)
        cut = [values[e - k : e][later[e - k : e]].tobytes() for e, k in zip(ends, sizes)]
        return pa.table([table.column("batch"), table.column("shard"), pa.array(cut, pa.binary())], ["batch", "shard", "flags"])

    def remove(table: pa.Table, told: pa.Table) -> pa.Table:
        out: list[list] = [[], [], [], [], [], []]
        if len(table):
            own = Batch(table, length)
            earlier = np.isin(own.distinct, joined(told, "u8"))
            group = own.group()
            # ids ascend with documents: a window is repeated under a smaller id within the batch, or elsewhere
            least = own.ids[own.doc[own.order[own.starts]]] if len(own.starts) else np.zeros(0, np.int64)
            bad = earlier[group] | (own.ids[own.doc] > least[group]) if len(group) else np.zeros(0, bool)
            ends = np.cumsum(own.sizes)
            for i, words in enumerate(own.words):
                starts = np.flatnonzero(bad[ends[i] - own.sizes[i] : ends[i]])
                gone = merged(starts, length, len(words))
                edges = np.flatnonzero(np.diff(np.concatenate(([0], gone.view(np.int8), [0])))).reshape(-1, 2)
                kept = b" ".join([w for w, g in zip(words, gone.tolist()) if not g] if len(starts) else words)
                got = (own.ids[i], len(words), int(gone.sum()), edges.tolist(), kept.decode(), hashlib.sha256(kept).hexdigest())
                for column, value in zip(out, got):
                    column.append(value)
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.list_(pa.int64())), pa.string(), pa.string())
        columns = [null_ids(np.array(out[0], np.int64)), *[pa.array(c, k) for c, k in zip(out[1:], kinds)]]
        return pa.table(columns, ["doc_id", "n_words", "n_removed", "intervals", "kept", "kept_sha256"])

    sent = rows.groupBy("batch").applyInArrow(lambda t: relieved(send_all(t)), "shard int, batch int, hashes binary")
    often = sent.groupBy("shard").applyInArrow(lambda t: relieved(count(t)), "batch int, shard int, flags binary")
    again = rows.groupBy("batch").cogroup(often.groupBy("batch")).applyInArrow(lambda t, u: relieved(send_often(t, u)), "shard int, batch int, hashes binary, others binary, ids binary")
    earlier = again.groupBy("shard").applyInArrow(lambda t: relieved(judge(t)), "batch int, shard int, flags binary")
    result = "doc_id long, n_words long, n_removed long, intervals array<array<long>>, kept string, kept_sha256 string"
    return rows.groupBy("batch").cogroup(earlier.groupBy("batch")).applyInArrow(lambda t, u: relieved(remove(t, u)), result)


def op9_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_words(documents(spark, sf_dir)).select("doc_id", "n_words", "n_removed", "kept_sha256")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op9_substrings": op9_substrings}
SQL: dict[str, str] = {
    "op9_substrings": rf"""
WITH split AS (
    SELECT doc_id, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS words FROM documents),
starts AS (
    SELECT doc_id, words, unnest(generate_series(1, len(words) - {LENGTH - 1})) AS start FROM split),
found AS (
    SELECT doc_id, start, doc_id > min(doc_id) OVER (PARTITION BY array_to_string(words[start : start + {LENGTH - 1}], ' ')) AS repeated FROM starts),
gone AS (
    SELECT DISTINCT doc_id, unnest(generate_series(start, start + {LENGTH - 1})) AS place FROM found WHERE repeated),
word AS (
    SELECT doc_id, unnest(words) AS w, generate_subscripts(words, 1) AS place FROM split),
kept AS (
    SELECT doc_id, count(g.place) AS n_removed, string_agg(w, ' ' ORDER BY place) FILTER (WHERE g.place IS NULL) AS rest
    FROM word LEFT JOIN gone g USING (doc_id, place) GROUP BY doc_id)
SELECT doc_id, len(words)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(rest, '')) AS kept_sha256
FROM split LEFT JOIN kept USING (doc_id)""",
}
