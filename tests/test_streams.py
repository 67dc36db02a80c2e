import uuid

import pytest
from pyspark.sql import functions as F

from rowgraph.streaming import stream


@pytest.fixture()
def events(spark, sf, tmp_path):
    table = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    table.repartitionByRange(3, "ts").write.parquet(f"{tmp_path}/e")
    return table, stream.read_facts(spark, f"{tmp_path}/e", table.schema, files=1000)


def name():
    return f"s_{uuid.uuid4().hex}"


def test_edges_equal_the_batch(events):
    table, live = events
    got = stream.drain(stream.edges(live, "event_id", "user_id", "ts"), name())
    want = table.select(F.col("event_id").alias("src"), F.col("user_id").alias("dst"), "ts")
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_sliding_features_equal_the_batch_once_mature(events):
    table, live = events
    got = stream.drain(stream.sliding_features(live, "user_id", "4 days", "2 days", "1 hour"), name())
    want = table.groupBy(F.window("ts", "4 days", "2 days"), "user_id").count().select(F.col("window.end").alias("seed_time"), "user_id", F.col("count").alias("n"))
    assert got.count() > 0 and got.exceptAll(want).count() == 0


def test_bursts_equal_the_batch(events):
    table, live = events
    got = stream.drain(stream.bursts(live, "user_id", "1 day", "1 hour"), name())
    want = {(r["user_id"], r["started"], r["n"]) for r in stream.batch_bursts(table, "user_id", 86400).collect()}
    have = {(r["user_id"], r["started"], r["n"]) for r in got.collect()}
    assert have and have <= want


def test_dimension_and_interval_joins(spark, sf, events):
    table, live = events
    dim = spark.read.parquet(f"{sf}/customer.parquet").select("c_custkey", "c_mktsegment")
    assert stream.drain(stream.with_dimension(live, dim, "user_id", "c_custkey"), name()).count() == table.count()
    clicks, buys = live.filter("event_type = 'click'"), live.filter("event_type = 'purchase'")
    got = stream.drain(stream.interval_join(clicks, buys, "user_id", "1 day", "40 days"), name())
    want = table.filter("event_type = 'click'").alias("a").join(table.filter("event_type = 'purchase'").alias("b"), F.expr("a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 day")).count()
    assert got.count() == want


def test_repeated_rows_pass_once(spark, sf, tmp_path):
    table = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    table.unionByName(table).write.parquet(f"{tmp_path}/e")
    live = stream.read_facts(spark, f"{tmp_path}/e", table.schema, files=1000)
    assert stream.drain(stream.distinct_rows(live, "event_id", "40 days"), name()).count() == table.count()


def test_late_rows_are_counted(spark, tmp_path):
    for k, hours in enumerate(([0, 1, 2], [50, 51], [3, 60])):
        rows = spark.createDataFrame([(h,) for h in hours], "h int").select(F.timestamp_seconds(F.lit(1_700_000_000) + F.col("h") * 3600).alias("ts"))
        rows.coalesce(1).write.mode("append").parquet(f"{tmp_path}/e")
        seen = {} if k == 0 else seen
        live = stream.read_facts(spark, f"{tmp_path}/e", rows.schema, files=1000)
        q = stream.count_late(live, seen, 3600).option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
        q.awaitTermination()
    assert seen["n"] == 7 and seen["late"] == 1
