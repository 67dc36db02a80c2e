"""Growing facts: labels, features, neighbours and links as Structured Streaming."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.columns import micros


def read_facts(spark: SparkSession, path: str, schema: T.StructType, files: int = 1) -> DataFrame:
    """A folder to which files of facts are added."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def edges(facts: DataFrame, pk: str, fk: str, time: str) -> DataFrame:
    """src, dst, ts of new rows; nothing is kept between batches.  Null references are no edges."""
    return facts.filter(F.col(fk).isNotNull()).select(F.col(pk).alias("src"), F.col(fk).alias("dst"), F.col(time).alias("ts"))


def mature_labels(facts: DataFrame, key: str, delta: str, late: str, aggs: dict[str, Column]) -> DataFrame:
    """Tumbling windows of the label width.  In append mode a window is given out once the watermark has passed its end,
    so a label is never given out before it is final."""
    out = facts.withWatermark("ts", late).groupBy(F.window("ts", delta), key).agg(*(c.alias(n) for n, c in aggs.items()))
    return out.select(F.col("window.start").alias("seed_time"), key, *aggs)


def sliding_features(facts: DataFrame, key: str, width: str, stride: str, late: str) -> DataFrame:
    """Counts over sliding look-back windows: seed_time is the window's end."""
    return facts.withWatermark("ts", late).groupBy(F.window("ts", width, stride), key).agg(F.count("*").alias("n")).select(F.col("window.end").alias("seed_time"), key, "n")


def bursts(facts: DataFrame, key: str, gap: str, late: str) -> DataFrame:
    """Activity bursts as nodes: sessions with a gap."""
    out = facts.withWatermark("ts", late).groupBy(F.session_window("ts", gap), key).agg(F.count("*").alias("n"))
    return out.select(key, F.col("session_window.start").alias("started"), F.col("session_window.end").alias("ended"), "n")


def batch_bursts(facts: DataFrame, key: str, gap_seconds: int, clock: Column | None = None) -> DataFrame:
    """The same over a table: a burst begins where the gap to the row before is too long.

    ``clock`` gives a row's second; without it times count to the microsecond, as in a stream.  Rows without time come
    last, each a burst of its own.
    """
    from pyspark.sql import Window

    w = Window.partitionBy(key).orderBy(F.col("ts").asc_nulls_last(), F.col("event_id").asc_nulls_last())
    if clock is None:
        clock, gap = F.unix_micros("ts") if dict(facts.dtypes)["ts"] == "timestamp" else micros(F.col("ts")), gap_seconds * 1000000
    else:
        gap = gap_seconds
    rows = facts.withColumn("clock_", clock)
    since = F.col("clock_") - F.lag("clock_").over(w)
    marked = rows.withColumn("new_", (F.coalesce(since, F.lit(gap)) >= gap).cast("int")).withColumn("burst", F.sum("new_").over(w))
    return marked.groupBy(key, "burst").agg(F.min("ts").alias("started"), F.max("ts").alias("ended"), F.count("*").alias("n"))


def latest_neighbours(facts: DataFrame, key: str, item: str, m: int, late: str) -> DataFrame:
    """Each node's latest m neighbours as state: key, version, items (comma-separated, latest first), given out on every change.

    State of a node is at most m (time, item) pairs and times out when the watermark passes its newest by the lateness.
    Of a node's rows that with the largest version, the number of facts seen so far, is the one that counts.  ``key`` and
    ``item`` are longs.
    """
    schema = f"{key} long, version long, items string"
    wait = int(pd.Timedelta(late).total_seconds() * 1000)

    def update(k, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        times, items, version = state.get if state.exists else ([], [], 0)
        held = list(zip(times, items, strict=True))
        for pdf in batches:
            version += len(pdf)
            held += zip(pdf["ts"].astype("int64").tolist(), pdf[item].astype("int64").tolist(), strict=True)
            held = sorted(set(held), key=lambda x: (-x[0], x[1]))[:m]
        state.update(([t for t, _ in held], [i for _, i in held], version))
        state.setTimeoutTimestamp(max(held[0][0] // 1_000_000 + wait, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({key: [k[0]], "version": [version], "items": [",".join(str(i) for _, i in held)]})

    return facts.withWatermark("ts", late).groupBy(key).applyInPandasWithState(update, schema, "times array<long>, items array<long>, version long", "update", "EventTimeTimeout")


def distinct_rows(facts: DataFrame, pk: str, late: str) -> DataFrame:
    return facts.withWatermark("ts", late).dropDuplicatesWithinWatermark([pk])


def with_dimension(facts: DataFrame, dim: DataFrame, fk: str, pk: str) -> DataFrame:
    """Stream rows with the attributes of a table."""
    return facts.join(dim, F.col(fk) == F.col(pk), "left")


def interval_join(a: DataFrame, b: DataFrame, key: str, within: str, late: str) -> DataFrame:
    """Rows of two streams of one key, b at most ``within`` after a; both sides' state is bounded by the watermarks."""
    left = a.withWatermark("ts", late).select(F.col(key).alias("key_a"), F.col("ts").alias("ts_a"), F.col("event_id").alias("id_a"))
    right = b.withWatermark("ts", late).select(F.col(key).alias("key_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("id_b"))
    return left.join(right, F.expr(f"key_a = key_b and ts_b >= ts_a and ts_b <= ts_a + interval {within}"))


def to_files(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now into Parquet files and returns them as a table.

    In update mode each batch's changed rows are files of their own, written over if the batch is run again.
    """
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/progress").trigger(availableNow=True)
    if mode == "append":
        q = writer.format("parquet").option("path", f"{path}/rows").start()
    else:
        q = writer.foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{path}/rows/batch_id={n}")).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/rows")


def drain(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all that is there now into a memory table and returns it; for tests and small results."""
    writer = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q = writer.start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def count_late(facts: DataFrame, batch_seen: dict, late_seconds: int):
    """A foreachBatch function that counts rows older than the newest time seen before the batch less the lateness."""

    def each(df: DataFrame, _: int) -> None:
        limit = batch_seen.get("newest")
        row = df.agg(F.max("ts").alias("hi"), F.count("*").alias("n")).first()
        if limit is not None:
            batch_seen["late"] = batch_seen.get("late", 0) + df.filter(F.col("ts").cast("double") < limit - late_seconds).count()
        if row["hi"] is not None:
            batch_seen["newest"] = max(limit or 0, row["hi"].timestamp())
        batch_seen["n"] = batch_seen.get("n", 0) + row["n"]

    return facts.writeStream.foreachBatch(each)
