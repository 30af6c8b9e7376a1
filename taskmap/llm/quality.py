"""Quality by logistic regression over hashed word n-grams, trained with follow-the-regularised-leader updates.

Features are words and pairs of neighbouring words, once as they stand and once as shapes (runs of letters, capitals and
digits reduced to one sign each, marks kept), hashed into 2^BITS slots. A document's vector holds each n-gram's share of
all its n-grams times SCALE. The fit goes over a bounded sample of labelled rows (SAMPLE), the score is a sparse dot
product over the whole text, in one mapInArrow over the scan and without a shuffle; the weights (2^BITS floats, whatever
the corpus size) travel with the task.

Defined results: null and empty texts have no feature and score the intercept; without labels of both kinds the score is
a constant; repeated ids are scored each.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.llm.common import U64, documents, sliced, table, text_bytes, texts
from taskmap.llm.learning import fitted, fold, labelled_sample, sigmoid

#: Labelled rows learnt from at most: label 0, label 1.
SAMPLE = (6000, 6000)
BITS = 18
SCALE = 24.0
THRESHOLD = 0.3
CACHE = 400_000

LOWER, UPPER, DIGIT = re.compile(r"[^\W\d_A-Z]+"), re.compile(r"[A-Z]+"), re.compile(r"\d+")


def shape(word: str) -> str:
    return DIGIT.sub("9", UPPER.sub("A", LOWER.sub("a", word)))


class Hasher:
    """Slots of n-grams. Words are hashed once each; a full cache starts anew."""

    def __init__(self) -> None:
        self.known: dict[bytes, tuple[int, int]] = {}

    def word(self, word: bytes) -> tuple[int, int]:
        import xxhash

        got = (xxhash.xxh3_64_intdigest(word), xxhash.xxh3_64_intdigest(shape(word.decode()).encode(), 1))
        if len(self.known) >= CACHE:
            self.known.clear()
        if len(word) <= 64:
            self.known[word] = got
        return got

    def slots(self, text: bytes) -> np.ndarray:
        split = text.split()
        if not split:
            return np.zeros(0, np.int64)
        known, slow = self.known.get, self.word
        both = np.array([known(w) or slow(w) for w in split], U64).reshape(-1, 2)
        runs = [both[:, 0], both[:, 1]]
        runs += [one[:-1] * U64(0x9DDFEA08EB382D69) + (one[1:] ^ (one[1:] >> U64(29))) * U64(0xD6E8FEB86659FD93) for one in runs]
        return (np.concatenate(runs) >> U64(64 - BITS)).astype(np.int64)


@dataclass(frozen=True)
class QualityModel:
    weights: np.ndarray
    intercept: float

    def score(self, slots: np.ndarray) -> float:
        return float(sigmoid(self.intercept + (SCALE * float(self.weights[slots].mean()) if len(slots) else 0.0)))


class FTRL:
    """Per-coordinate follow-the-regularised-leader with L1 and L2 terms."""

    def __init__(self, n: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02):
        self.z, self.n = np.zeros(n), np.zeros(n)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at: np.ndarray | slice) -> np.ndarray:
        z = self.z[at]
        shrunk = np.sign(z) * np.maximum(np.abs(z) - self.l1, 0)
        return -shrunk / ((self.beta + np.sqrt(self.n[at])) / self.alpha + self.l2)

    def learn(self, at: np.ndarray, x: np.ndarray, y: float) -> None:
        w = self.weights(at)
        g = (sigmoid(float(w @ x)) - y) * x
        grown = self.n[at] + g * g
        self.z[at] += g - (np.sqrt(grown) - np.sqrt(self.n[at])) / self.alpha * w
        self.n[at] = grown


def fit(sample: list[tuple[int, str]], passes: int = 3) -> QualityModel:
    bias = 1 << BITS
    learner, hasher = FTRL(bias + 1), Hasher()
    seen = []
    for y, text in sample:
        at, count = np.unique(hasher.slots(text.encode()), return_counts=True)
        seen.append((np.append(at, bias).astype(np.int32), np.append(SCALE * count / max(1, count.sum()), 1.0).astype(np.float32), float(y)))
    for _ in range(passes):
        for at, x, y in seen:
            learner.learn(at, x, y)
    w = learner.weights(slice(None))
    return QualityModel(w[:bias].astype(np.float32), float(w[bias]))


def score_documents(docs: DataFrame, model: QualityModel) -> DataFrame:
    """doc_id, score, predicted."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2^BITS floats

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, hasher = shared.value, Hasher()
        for batch in sliced(batches):
            score = np.array([own.score(hasher.slots(raw)) for raw in text_bytes(batch.column("text"))], float)
            columns = [batch.column("doc_id"), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "score", "predicted"])

    return texts(docs).mapInArrow(run, "doc_id long, score double, predicted int")


def keep_good(docs: DataFrame, model: QualityModel) -> DataFrame:
    """The documents that the model accepts, with all their columns, in one pass over the scan."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, hasher = shared.value, Hasher()
        for batch in sliced(batches):
            kept = [own.score(hasher.slots(raw)) >= THRESHOLD for raw in text_bytes(batch.column("text"))]
            yield batch.filter(pa.array(kept, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def trained(spark: SparkSession, docs: DataFrame, sf_dir: str) -> QualityModel:
    labels = table(spark, sf_dir, "labels")
    return fitted(labelled_sample(docs, labels, "quality", fold(F.col("doc_id"), 5) != 0, SAMPLE), fit)


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    held_out = F.coalesce(fold(F.col("doc_id"), 5) == 0, F.lit(False))
    return score_documents(docs, trained(spark, docs, sf_dir)).select("doc_id", held_out.alias("held_out"), "score", "predicted")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op5_quality": op5_quality}
SQL: dict[str, str] = {}
