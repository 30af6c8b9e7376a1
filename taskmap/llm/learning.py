"""What the two classifiers share: a bounded sample of labelled documents, folds by id, small logistic fits."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from taskmap.llm.common import texts

#: Longest text, in bytes, that is learnt from. Scoring has no such bound.
LEARN_BYTES = 1 << 16


def fold(doc_id: Column, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(n)).cast("int")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, learn: Column, bounds: tuple[int, int]) -> DataFrame:
    """Up to bounds[0] texts of label 0 and bounds[1] of label 1 whose id passes learn, as o (a hash of the id), doc_id, y, text.

    The ids are chosen first, from the labels alone, so that what is broadcast to the documents has at most
    sum(bounds) rows. Ids with contradictory labels have label 1. Rows without a label or an id take no part.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
    known = known.filter(F.col("doc_id").isNotNull() & F.col("y").isin(0, 1) & learn).groupBy("doc_id").agg(F.max("y").alias("y"))
    order = F.xxhash64("doc_id", F.lit(11))
    picked = [known.filter(F.col("y") == y).orderBy(order, "doc_id").limit(n) for y, n in enumerate(bounds)]
    ids = F.broadcast(picked[0].unionByName(picked[1]))
    found = texts(docs).filter(F.octet_length("text") <= LEARN_BYTES).join(ids, "doc_id")
    return found.select(order.alias("o"), "doc_id", "y", "text")


def fitted(sample: DataFrame, fit: Callable[[list[tuple[int, str]]], Any]) -> Any:
    """What fit makes of a labelled sample, as (label, text) by the hash of the id; equal texts count once.

    It runs in one task on an executor, as its input is bounded, and only the model comes back to the driver.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [row for batch in batches for row in zip(*(column.to_pylist() for column in batch.columns))]
        seen: dict[str, int] = {}
        for _, _, y, text in sorted(rows, key=lambda r: (r[0], r[1], r[3])):
            seen.setdefault(text, y)
        del rows
        model = fit([(y, text) for text, y in seen.items()])
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])

    got = sample.repartition(1).mapInArrow(run, "model binary").collect()
    return pickle.loads(got[0]["model"]) if got else fit([])


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 60) -> np.ndarray:
    """Weights (intercept last) of a ridge-penalised logistic regression, by damped Newton steps. Without both labels: a constant."""
    x = np.column_stack([x, np.ones(len(x))]) if len(x) else np.zeros((0, x.shape[1] + 1))
    w = np.zeros(x.shape[1])
    if len(y) == 0 or y.min() == y.max():
        w[-1] = 0.0 if len(y) == 0 else (4.0 if y[0] else -4.0)
        return w
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) / len(y) + ridge * np.append(w[:-1], 0) / len(y)
        h = (x * (p * (1 - p))[:, None]).T @ x / len(y) + np.eye(len(w)) * (ridge / len(y) + 1e-9)
        step = np.linalg.solve(h, g)
        w -= step / max(1.0, np.abs(step).max() / 4)
        if np.abs(step).max() < 1e-9:
            break
    return w


def sigmoid(z: np.ndarray | float) -> np.ndarray | float:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))
