"""Mixing sources to target weights by weighted fair queueing.

Each source is a queue of its documents in a shuffled order (by a hash of the id, other for each round through the
source). A document's virtual finish time is the number of words its source has sent when it has been sent, divided by
the source's target; all queues together, in the order of that time, are the mix. It ends at virtual time 1, where the
whole budget has been sent and every source its target; a document that is being sent then is cut there.

Targets share a budget by weight, but none passes MOST_ROUNDS times its source; what is above is shared anew by weight.
That fixed point has a closed form: in the order of cap / weight, sources are capped up to a point, and the rest share
what is left. It is found on the table of sources, one row for each.

Running sums do not gather a source in one task: the shuffled order falls into ranges of the hash, sums for each range
give every range its start, and only the rows of one range of one source are ordered together. The number of ranges
grows with the root of the input, so neither those nor the rows in one of them pile up.

Defined results: null text has size 0 and is taken 0 times; null source is a source (last in order); null ids are rows
like others; rows with equal ids are separate documents; an empty table gives no rows; other columns pass unchanged, whatever their names.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.llm.common import documents, ensure_checkpoints, size_estimate

WEIGHTS = (5, 2, 1)
#: The budget, as a share of all words.
BUDGET = 1.5
MOST_ROUNDS = 2
WORD = r"[^\x20\x09-\x0D]+"
SEED = 17
ADDED = ["size", "source_size", "target", "taken_first", "taken_again", "taken", "finish_first", "finish_again"]


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _shuffled(docs: DataFrame, keep: list[str], bits: int) -> DataFrame:
    """The columns to keep of docs (row), the size, the source as a key that is never null, the place in the shuffled order."""
    place = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(SEED)), F.col("doc_id").cast("string"))), 1, 15), 16, 10).cast("long")
    own = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"),
        F.col("doc_id").alias("doc"),
        F.col("source").isNull().alias("none"),
        F.coalesce("source", F.lit("")).alias("source"),
        word_count(F.col("text")).alias("size"),
        place.alias("place"),
    )
    return own.withColumn("range", F.shiftright("place", 60 - bits).cast("int"))


def targets(sources: DataFrame, weights: tuple[float, ...] = WEIGHTS, budget: float = BUDGET) -> DataFrame:
    """Of sources(none, source, source_size): with weight and target. One row for each source."""
    everything = W.partitionBy()
    rank = F.row_number().over(W.orderBy("none", "source")) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int"))
    own = sources.withColumn("weight", weight).withColumn("cap", F.lit(float(MOST_ROUNDS)) * F.col("source_size"))
    by_ratio = W.orderBy(F.col("cap") / F.col("weight"), "none", "source")
    before = by_ratio.rowsBetween(W.unboundedPreceding, -1)
    own = own.withColumns(
        {
            "left": F.lit(budget) * F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0.0)),
            "open": F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)),
        }
    )
    level = F.max(F.when(F.col("left") / F.col("open") * F.col("weight") <= F.col("cap"), F.col("left") / F.col("open"))).over(everything)
    # with everything capped there is no level
    target = F.least(F.col("cap"), F.coalesce(level * F.col("weight"), F.col("cap")))
    return own.select("none", "source", "source_size", "weight", target.alias("target"))


def _mixed(docs: DataFrame, keep: list[str], weights: tuple[float, ...] = WEIGHTS, budget: float = BUDGET) -> DataFrame:
    """row (a struct of the columns of docs to keep), doc (the id) and the columns that mix adds."""
    ensure_checkpoints(docs.sparkSession)
    bits = max(4, min(20, math.ceil(math.log2(max(1, size_estimate(docs)) / 1000 + 1) / 2)))
    rows = _shuffled(docs, keep, bits)
    ranges = rows.groupBy("none", "source", "range").agg(F.sum("size").alias("words")).checkpoint()
    sources = ranges.groupBy("none", "source").agg(F.sum("words").alias("source_size"))
    earlier = W.partitionBy("none", "source").orderBy("range").rowsBetween(W.unboundedPreceding, -1)
    starts = ranges.withColumn("start", F.coalesce(F.sum("words").over(earlier), F.lit(0)))
    starts = starts.join(targets(sources, weights, budget), ["none", "source"]).drop("words").checkpoint()

    within = W.partitionBy("none", "source", "range").orderBy("place", "doc", "size").rowsBetween(W.unboundedPreceding, -1)
    found = rows.join(starts, ["none", "source", "range"]).withColumn("before", F.col("start") + F.coalesce(F.sum("size").over(within), F.lit(0)))

    goal = F.round("target").cast("long")
    sent = lambda after: F.greatest(F.lit(0), F.least(F.col("size"), goal - after)).cast("long")
    first, again = sent(F.col("before")), sent(F.col("source_size") + F.col("before"))
    ended = lambda taken, after: F.when(taken > 0, F.least(F.lit(1.0), (after + taken) / F.col("target")))
    return found.select(
        "row",
        "doc",
        "size",
        "source_size",
        "target",
        first.alias("taken_first"),
        again.alias("taken_again"),
        (first + again).alias("taken"),
        ended(first, F.col("before")).alias("finish_first"),
        ended(again, F.col("source_size") + F.col("before")).alias("finish_again"),
    )


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, budget: float = BUDGET) -> DataFrame:
    """All columns of docs, with size, source_size, target, taken_first, taken_again (words sent in either round), taken
    (both), finish_first and finish_again (the virtual times when the sendings end; null where nothing is sent). Columns of
    docs that have one of these names give way."""
    keep = [c for c in docs.columns if c not in ADDED]
    return _mixed(docs, keep, weights, budget).select(*[F.col(f"row.`{c}`").alias(c) for c in keep], *ADDED)


def mixed_stream(docs: DataFrame, partitions: int, weights: tuple[float, ...] = WEIGHTS, budget: float = BUDGET) -> DataFrame:
    """The mix itself, in its global order: a row for each sending, the words sent as text where it is cut. The columns are
    those of docs, whatever their names."""
    found = _mixed(docs, docs.columns, weights, budget)
    one = lambda which: F.struct(F.col(f"taken_{which}").alias("n"), F.col(f"finish_{which}").alias("at"))
    rows = found.select("row", "doc", "size", F.explode(F.filter(F.array(one("first"), one("again")), lambda s: s["n"] > 0)).alias("sent"))
    cut = F.array_join(F.slice(F.regexp_extract_all("row.text", F.lit(WORD), F.lit(0)), 1, F.col("sent.n").cast("int")), " ")
    whole = F.col("sent.n") >= F.col("size")
    rows = rows.select("row", "doc", whole.alias("whole"), F.when(~whole, cut).alias("cut"), F.col("sent.at").alias("at"))
    rows = rows.repartitionByRange(partitions, "at").sortWithinPartitions("at", "doc")
    columns = []
    for c in docs.columns:
        own = F.col(f"row.`{c}`")
        if c == "text":
            own = F.when(F.col("whole"), own).otherwise(F.col("cut"))
        elif c == "n_chars":
            own = F.when(F.col("whole"), own).otherwise(F.length("cut")).cast(docs.schema[c].dataType)
        columns.append(own.alias(c))
    return rows.select(*columns)


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _mixed(documents(spark, sf_dir), ["doc_id"]).select("row.doc_id", "size", "source_size", "target", "taken")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op2_mixing": op2_mixing}
SQL: dict[str, str] = {
    "op2_mixing": rf"""
WITH sized AS (
    SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '{WORD}')), 0)::BIGINT AS size,
           substr(md5(concat_ws(':', '{SEED}', doc_id::VARCHAR)), 1, 15) AS place
    FROM documents),
sources AS (
    SELECT source, sum(size)::BIGINT AS source_size,
           CASE (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 WHEN 0 THEN {WEIGHTS[0]}.0 WHEN 1 THEN {WEIGHTS[1]}.0 ELSE {WEIGHTS[2]}.0 END::DOUBLE AS weight
    FROM sized GROUP BY source),
poured AS (
    SELECT *, {BUDGET}::DOUBLE * sum(source_size) OVER () - coalesce(sum({MOST_ROUNDS}.0::DOUBLE * source_size) OVER before, 0) AS rest,
           sum(weight) OVER () - coalesce(sum(weight) OVER before, 0) AS open
    FROM sources
    WINDOW before AS (ORDER BY {MOST_ROUNDS}.0::DOUBLE * source_size / weight, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
levels AS (
    SELECT *, max(CASE WHEN rest / open * weight <= {MOST_ROUNDS} * source_size THEN rest / open END) OVER () AS level FROM poured),
goals AS (
    SELECT source, source_size, least({MOST_ROUNDS}.0::DOUBLE * source_size, coalesce(level * weight, {MOST_ROUNDS}.0::DOUBLE * source_size)) AS target FROM levels),
queued AS (
    SELECT d.doc_id, d.size, g.source_size, g.target, round(g.target)::BIGINT AS goal,
           coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.place, d.doc_id NULLS FIRST, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS sent
    FROM sized d JOIN goals g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target,
       (greatest(0, least(size, goal - sent)) + greatest(0, least(size, goal - source_size - sent)))::BIGINT AS taken
FROM queued""",
}
