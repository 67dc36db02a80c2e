"""Times between whole seconds and rows without one: queries on events against their SQL."""

from datetime import datetime as D

import duckdb
import pytest
from pyspark.sql import functions as F

from rowgraph.queries import ORACLE, QUERIES
from rowgraph.streaming import stream

TIMES = [
    D(2024, 1, 8), D(2024, 1, 8, 0, 0, 0, 1), D(2024, 1, 8, 0, 0, 0, 400000), D(2024, 1, 1, 0, 0, 0, 600000), D(2024, 1, 14, 23, 59, 59, 999999), D(2024, 1, 15), D(2024, 1, 15, 0, 0, 0, 1),
    D(2024, 1, 20, 12, 0, 0, 500000), D(2024, 1, 21, 12, 0, 0, 400000), D(2024, 1, 22, 12, 0, 0, 400001), D(2024, 1, 23, 11, 59, 59, 900000), D(2024, 1, 27, 12, 0, 1, 500000), D(2024, 1, 29, 23, 59, 59), None,
]


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("odd"))
    rows = [(10 * u + k if u == 1 else 100 * u + k, t, u, float(k)) for u in (1, 2) for k, t in enumerate(TIMES)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, value double").coalesce(1).write.parquet(f"{d}/events.parquet")
    return d


def both(spark, d, name):
    df = QUERIES[name](spark, d)
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{d}/events.parquet/*.parquet'")
    found = con.sql(ORACLE[name])
    order = [df.columns.index(c) for c in found.columns]
    return sorted((tuple(r[i] for i in order) for r in df.collect()), key=repr), sorted(map(tuple, found.fetchall()), key=repr)


@pytest.mark.parametrize("zone", ["UTC", "America/New_York"])
def test_daily_features_on_odd_times(spark, odd, zone):
    spark.conf.set("spark.sql.session.timeZone", zone)
    try:
        got, want = both(spark, odd, "feat_daily")
    finally:
        spark.conf.set("spark.sql.session.timeZone", "UTC")
    assert got == want


def test_rolling_features_on_odd_times(spark, odd):
    got, want = both(spark, odd, "feat_rolling")
    assert got == want


def test_bursts_on_odd_times(spark, odd):
    got, want = both(spark, odd, "session_islands")
    assert got == want


def test_bursts_without_a_clock_count_to_the_microsecond(spark):
    rows = [(k, D(2024, 1, 1 + k, 0, 0, 0, us), 1) for k, us in enumerate((5, 4, 4))]
    facts = spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long")
    for table in (facts, facts.withColumn("ts", F.col("ts").cast("timestamp"))):
        assert sorted(r["n"] for r in stream.batch_bursts(table, "user_id", 86400).collect()) == [1, 2]
