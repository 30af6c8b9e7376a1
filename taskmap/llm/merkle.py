"""Document fingerprints: a Merkle tree over phrases, paragraphs and sections.

A leaf is a phrase (up to and with the next mark or line end, cut after PHRASE characters), a paragraph is a line, a
section a run of paragraphs that ends at an empty line or, where a paragraph's own hash says so, within plain lines.
Each inner node hashes its children's hashes, the root all sections; leaves cover the text wholly, so equal roots mean
equal texts. Two trees are compared from the top: equal sections count whole, then equal paragraphs among the rest, then
equal phrases. The likeness is the shared share of both texts' bytes; the parts left over locate an edit.

Fingerprints of all documents are one mapInArrow over the scan. Comparing each document with the next one in the order of
ids takes a single exchange: ids fall into ranges by approximate quantiles, each range is streamed in order within its
task, and a copy of the first document of the next range ends it. So no task sees more than its ranges, and what goes to
the driver is one id for each range.

Defined results: a null text is the empty text, whose root is the hash of no section; null ids come first; rows with
equal ids follow in the order of their texts, each the next one's predecessor; a single document is its own next.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.llm.common import NULL_ID, documents, null_ids, order_ids, parts_for, texts

PHRASE = 80
#: One in so many paragraphs ends a section, besides empty lines.
SECTION = 8

LEAVES = re.compile(r"[^.!?,;:|\n]{0,%d}[.!?,;:|]*[^\S\n]*\n?|\n" % PHRASE)


def digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


@dataclass
class Tree:
    """root; sections as (hash, bytes, paragraphs), paragraphs as (hash, bytes, phrases), phrases as strings."""

    root: bytes
    size: int
    sections: list[tuple[bytes, int, list[tuple[bytes, int, list[str]]]]]

    @property
    def fingerprint(self) -> str:
        return self.root.hex()


def tree(text: str | None) -> Tree:
    sections, current, total = [], [], 0
    for line in (text or "").splitlines(keepends=True):
        raw = line.encode()
        paragraph = (digest(raw), len(raw), line)
        current.append(paragraph)
        total += len(raw)
        if not line.strip() or paragraph[0][0] % SECTION == 0:
            sections.append((digest(b"".join(p[0] for p in current)), sum(p[1] for p in current), current))
            current = []
    if current:
        sections.append((digest(b"".join(p[0] for p in current)), sum(p[1] for p in current), current))
    return Tree(digest(b"".join(s[0] for s in sections)), total, sections)


def phrases(line: str) -> list[str]:
    return [x for x in LEAVES.findall(line) if x]


def _unmatched(ours: list, theirs: list) -> tuple[int, list, list]:
    """Pairs off nodes with equal hashes: their bytes, and what is left on both sides."""
    have = Counter(n[0] for n in theirs)
    shared, left = 0, []
    for node in ours:
        if have[node[0]] > 0:
            have[node[0]] -= 1
            shared += node[1]
        else:
            left.append(node)
    rest = []
    for node in theirs:
        if have[node[0]] > 0:
            have[node[0]] -= 1
            rest.append(node)
    return shared, left, rest


def compare(a: Tree, b: Tree) -> tuple[float, list[str], list[str]]:
    """Likeness (0 to 1) and the phrases that only one side has, found by descending where hashes differ."""
    if a.root == b.root:
        return 1.0, [], []
    if not a.size or not b.size:
        return 0.0, [p for s in a.sections for l in s[2] for p in phrases(l[2])], [p for s in b.sections for l in s[2] for p in phrases(l[2])]
    shared, left, right = _unmatched(a.sections, b.sections)
    more, left, right = _unmatched([p for s in left for p in s[2]], [p for s in right for p in s[2]])
    leaf = lambda lines: [(x, len(x.encode()), x) for p in lines for x in phrases(p[2])]
    last, left, right = _unmatched(leaf(left), leaf(right))
    return 2 * (shared + more + last) / (a.size + b.size), [x[2] for x in left], [x[2] for x in right]


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint, n_sections, n_paragraphs: one pass over the scan."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            trees = [tree(t) for t in batch.column("text").to_pylist()]
            columns = [batch.column("doc_id"), pa.array([t.fingerprint for t in trees], pa.string()), pa.array([len(t.sections) for t in trees], pa.int32()), pa.array([sum(len(s[2]) for s in t.sections) for t in trees], pa.int32())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "fingerprint", "n_sections", "n_paragraphs"])

    return texts(docs).mapInArrow(run, "doc_id long, fingerprint string, n_sections int, n_paragraphs int")


def edited(text: str, following: str) -> str:
    """The last half of the text gives way to the beginning of another."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def with_next(docs: DataFrame, ranges: int) -> DataFrame:
    """doc_id, text and ghost in ranges of ids, each followed by the first document of the next range (ghost = true).

    The last range is followed by the first document of all.
    """
    spark = docs.sparkSession
    rows = texts(docs).withColumn("doc_id", F.coalesce("doc_id", F.lit(NULL_ID)))
    cuts = rows.agg(F.percentile_approx("doc_id", F.lit([i / ranges for i in range(1, ranges)] or [0.5]), F.lit(20 * ranges)).alias("q"), F.min("doc_id").alias("first")).head()
    bounds = sorted(set(cuts["q"] or []) - {cuts["first"]}) if ranges > 1 else []
    where = np.array(bounds, np.int64)
    # bounds are ids that exist: each begins its range, so the ghosts are known by their ids
    ghosts = spark.createDataFrame([(b, i) for i, b in enumerate(bounds)] + [(cuts["first"], len(bounds))] if cuts["first"] is not None else [], "doc_id long, range int")
    ghosts = rows.join(F.broadcast(ghosts), "doc_id").select("range", "doc_id", "text", F.lit(True).alias("ghost"))
    last = ghosts.schema["range"].dataType

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = np.searchsorted(where, batch.column("doc_id").to_numpy(), side="right").astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), batch.column("doc_id"), batch.column("text"), pa.array(np.zeros(len(at), bool))], ["range", "doc_id", "text", "ghost"])

    own = rows.mapInArrow(place, "range int, doc_id long, text string, ghost boolean")
    both = own.unionByName(ghosts.withColumn("range", F.col("range").cast(last)))
    width = max(1, min(ranges, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    return both.repartition(width, "range").sortWithinPartitions("range", "ghost", "doc_id", "text")


def compared_with_next(docs: DataFrame, ranges: int) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[int, int, str, Tree] | None = None
        for batch in batches:
            out: list[list] = [[] for _ in range(7)]
            for part, doc_id, text, ghost in zip(batch.column("range").to_pylist(), order_ids(batch.column("doc_id")).tolist(), batch.column("text").to_pylist(), batch.column("ghost").to_pylist()):
                own = tree(text)
                if held is not None and held[0] == part:
                    _, at, before, known = held
                    changed = edited(before, text)
                    other = tree(changed)
                    got = (at, len(before), hashlib.sha256(changed.encode()).hexdigest(), known.fingerprint, other.fingerprint, compare(known, other)[0], compare(known, own)[0])
                    for column, value in zip(out, got):
                        column.append(value)
                held = None if ghost else (part, doc_id, text, own)
            kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            columns = [null_ids(np.array(out[0], np.int64)), *[pa.array(c, k) for c, k in zip(out[1:], kinds)]]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return with_next(docs, ranges).mapInArrow(run, schema)


def op4_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return compared_with_next(docs, 4 * max(parts_for(docs, 4), int(spark.conf.get("spark.sql.shuffle.partitions"))))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op4_merkle": op4_merkle}
SQL: dict[str, str] = {}
