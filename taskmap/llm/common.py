"""Helpers that several corpus operators share.

Every helper is total: null ids sort before all others, a null text counts as the empty text, and columns that an
operator does not need are never read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: What stands for a null doc_id inside operators: it sorts before every other id.
NULL_ID = -(1 << 63)

U64 = np.uint64

#: Runtime setting: shuffle files go when the query that wrote them has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame, *more: Column) -> DataFrame:
    """doc_id and text under their own names, whatever else the table holds; a null text becomes the empty one."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


#: From here on an estimate is no knowledge: sources without statistics count as 2^63 bytes.
UNKNOWN = 1 << 55


def size_estimate(df: DataFrame) -> int:
    """Bytes of the input as the optimizer knows them from file sizes. Where it doesn't know (or multiplies the sides of a
    join), a job adds up the texts."""
    plan = df._jdf.queryExecution().optimizedPlan()
    stats = int(str(plan.stats().sizeInBytes()))
    if stats < UNKNOWN and "Join " not in plan.toString():
        return stats
    told = df.agg(F.sum(F.octet_length("text")) if "text" in df.columns else F.count("*") * 1000).head()[0]
    return int(told or 0)


def parts_for(df: DataFrame, target_mb: float, least: int = 1, most: int = 1 << 20) -> int:
    """A number of partitions that grows with the input, so that one partition holds about target_mb of files."""
    return max(least, min(most, math.ceil(size_estimate(df) / (target_mb * 1e6))))


def batch_of(doc_id: Column, n: int) -> Column:
    """The batch of a document: a hash of its id, so that equal ids meet and no batch depends on the file layout."""
    return F.pmod(F.xxhash64(F.coalesce(doc_id, F.lit(NULL_ID)), F.lit(7)), F.lit(n)).cast("int")


def order_ids(ids: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """int64 ids with NULL_ID for nulls."""
    return ids.fill_null(NULL_ID).to_numpy(zero_copy_only=False).astype(np.int64, copy=False)


def null_ids(ids: np.ndarray) -> pa.Array:
    """The reverse of order_ids."""
    return pa.array(ids, pa.int64(), mask=ids == NULL_ID)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of uint64 values (two rounds of xor-shift and odd multiplication)."""
    x = x ^ (x >> U64(31))
    x = x * U64(0x7FB5D329728EA185)
    x = x ^ (x >> U64(27))
    x = x * U64(0x81DADEF4BC2DD44D)
    return x ^ (x >> U64(33))


def text_bytes(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """The UTF-8 bytes of each text; nulls are empty."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]


def sliced(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """Record batches in short slices, so that what is made of texts in Python is held for a few of them only."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def checkpoint_dir(spark: SparkSession) -> str | None:
    """The shared folder for checkpoints, as the session names it."""
    return spark.conf.get("spark.checkpoint.dir", None)


def ensure_checkpoints(spark: SparkSession) -> None:
    """Use the folder of spark.checkpoint.dir; only where nothing names one, as in tests, take a local folder."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    named = checkpoint_dir(spark)
    if named is None:
        import tempfile

        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = tempfile.mkdtemp(prefix="checkpoints-")
    context.setCheckpointDir(named)


def relieved(result: pa.Table) -> pa.Table:
    """Hands freed memory back to the system after a group, so that a worker's size follows its largest group only."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # another C library
    return result


def stored(df: DataFrame) -> DataFrame:
    """The rows as a compressed table in the shared folder for checkpoints: cuts the lineage, outlives executors."""
    import uuid

    spark = df.sparkSession
    ensure_checkpoints(spark)
    path = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/rows-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")  # of this write: nothing reads its shuffles later
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        if before is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)

