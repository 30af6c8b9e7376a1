"""What iterated plans need: a barrier that ends a round's plan, and clocks."""

from __future__ import annotations

import time
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoints(spark: SparkSession) -> None:
    """Checkpoints go to the folder in spark.checkpoint.dir; only where nothing names one, as in tests, to a local one."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None:
        import tempfile

        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = tempfile.mkdtemp(prefix="checkpoints-")
    context.setCheckpointDir(named)


#: Runtime setting: whether unions keep a common partitioning of their inputs. Where inputs are read with other numbers of
#: partitions than planned, such a union fails.
UNIONS = "spark.sql.unionOutputPartitioning"


@contextmanager
def steady(spark: SparkSession):
    """While plans run whose unions are of tables of all sizes."""
    before = spark.conf.get(UNIONS, None)
    spark.conf.set(UNIONS, "false")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(UNIONS)
        else:
            spark.conf.set(UNIONS, before)


def barrier(df: DataFrame) -> DataFrame:
    """The rows as a table in the folder for checkpoints, which outlives executors; plans built on it start there.

    Written once (a checkpoint computes its rows twice), and the files' sizes tell later joins which side is small.
    """
    spark = df.sparkSession
    ensure_checkpoints(spark)
    path = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/barrier-{uuid.uuid4().hex}"
    with steady(spark):
        df.write.parquet(path)
    held = spark.read.schema(df.schema).parquet(path)
    held.stored_at = path
    return held


def release(*tables: DataFrame) -> None:
    """Deletes what barriers stored and no plan needs any more."""
    for df in tables:
        path = getattr(df, "stored_at", None)
        if path is not None:
            spark = df.sparkSession
            folder = spark._jvm.org.apache.hadoop.fs.Path(path)
            folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


class Clock:
    """Seconds by phase, as rows of a round log."""

    def __init__(self) -> None:
        self.rows: list[dict] = []

    @contextmanager
    def phase(self, name: str, level: int = 0, **more):
        began = time.perf_counter()
        row = {"phase": name, "level": level, **more}
        try:
            yield row
        finally:
            row["seconds"] = time.perf_counter() - began
            self.rows.append(row)

    def seconds(self) -> dict[str, float]:
        out: dict[str, float] = {}
        for r in self.rows:
            out[r["phase"]] = out.get(r["phase"], 0.0) + r["seconds"]
        return out
