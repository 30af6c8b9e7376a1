"""Streams give what their batch twins give."""

from pyspark.sql import functions as F

from taskmap.sources.generators import grid
from taskmap.streaming import edges as st
from taskmap.topology import Topology


def staged(spark, tiny, tmp_path):
    events = spark.read.parquet(f"{tiny}/events.parquet").select("event_id", "ts", "user_id").orderBy("ts").limit(300)
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    return events, spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))


def drained(df, name, mode="append"):
    query = df.writeStream.outputMode(mode).format("memory").queryName(name).start()
    query.processAllAvailable()
    query.stop()
    return df.sparkSession.table(name)


def test_window_edges(spark, tiny, tmp_path):
    batch, stream = staged(spark, tiny, tmp_path)
    got = drained(st.window_edges(stream, "10 minutes"), "w_edges")
    batch = batch.withColumn("ts", F.col("ts").cast("timestamp"))
    last = batch.agg(F.max("ts")).head()[0]
    want = st.window_edges(batch, "10 minutes").filter(F.col("start") + F.expr("INTERVAL 41 MINUTES") < F.lit(last))
    # windows that the watermark has closed are complete and equal
    assert not want.exceptAll(got.select(want.columns)).count()


def test_handoffs(spark, tiny, tmp_path):
    batch, stream = staged(spark, tiny, tmp_path)
    got = drained(st.handoffs(stream.withColumn("lane", F.lit("all")), "lane"), "handoffs")
    users = [r["user_id"] for r in batch.orderBy("ts", "event_id").collect()]
    assert sorted((r["a"], r["b"]) for r in got.collect()) == sorted((a, b) for a, b in zip(users, users[1:]) if a != b)


def test_distinct_events_and_sessions(spark, tiny, tmp_path):
    batch, stream = staged(spark, tiny, tmp_path)
    twice = stream.unionByName(stream)
    assert drained(st.distinct_events(twice), "once").count() == batch.count()
    assert st.session_counts(batch).agg(F.sum("n")).head()[0] == batch.count()


def test_repair_follows_new_edges(spark):
    g = grid(spark, 4, 4)
    m = g.vertices.selectExpr("id", "cast(id % 4 as int) as pe")
    repair = st.Repair(g.edges, m, Topology.parse("2:2", "1:10"))
    repair(spark.createDataFrame([(0, 5, 50), (16, 0, 3)], "a long, b long, w long"), 0)
    after = {r["id"]: r["pe"] for r in repair.mapping.collect()}
    assert len(after) == 17 and after[0] == after[5]
    live = st.live_objective(spark.createDataFrame([(0, 5, 2)], "a long, b long, w long").withColumn("start", F.lit(0)), repair.mapping, Topology.parse("2:2", "1:10"))
    assert live.agg(F.sum("x")).head()[0] == 0
