"""Split times and seed times."""

from __future__ import annotations

from dataclasses import dataclass
from datetime import datetime, timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import micros


@dataclass(frozen=True)
class SplitSpec:
    """Validation and test time of a database, shared by its tasks, and the span of the tables that labels read."""

    t_val: datetime
    t_test: datetime
    min_time: datetime
    max_time: datetime

    def check(self, delta: int, allow_overrun: bool = False) -> SplitSpec:
        width = timedelta(days=delta)
        if self.t_val >= self.t_test:
            raise ValueError("validation must come before test")
        if self.t_val + width > self.t_test and not allow_overrun:
            raise ValueError("the validation window passes the test time")
        if self.t_test + width >= self.max_time:
            raise ValueError("the test window isn't over in the data")
        return self


def stamp_list(split: SplitSpec, delta: int, stride: int | None = None, min_history: int = 0, max_stamps: int | None = None) -> list[tuple[str, datetime]]:
    """(split, seed time): training stamps walk back from t_val - delta, so that their windows end by t_val."""
    step = timedelta(days=stride or delta)
    if step <= timedelta(0):
        raise ValueError("the stride must be positive")
    out, t = [("val", split.t_val), ("test", split.t_test)], split.t_val - timedelta(days=delta)
    while t >= split.min_time + timedelta(days=min_history) and (max_stamps is None or len(out) < max_stamps + 2):
        out.append(("train", t))
        t -= step
    return out


def stamps(spark: SparkSession, split: SplitSpec, delta: int, stride: int | None = None, min_history: int = 0, max_stamps: int | None = None) -> DataFrame:
    return stamps_frame(spark, stamp_list(split, delta, stride, min_history, max_stamps))


def stamps_over(facts: DataFrame, ts: str, split: SplitSpec, delta: int, stride: int | None = None, min_history: int = 0) -> DataFrame:
    """The same, where training stamps go back to the first time of the facts themselves: one pass over their times."""
    step = timedelta(days=stride or delta)
    if step <= timedelta(0):
        raise ValueError("the stride must be positive")
    start = F.lit((split.t_val - timedelta(days=delta)).isoformat(" ")).cast("timestamp_ntz")
    stop = F.col("lo_").cast("timestamp_ntz") + F.make_dt_interval(days=F.lit(min_history))
    back = F.when(stop <= start, F.sequence(start, stop, F.make_dt_interval(days=F.lit(-step.days))))
    train = facts.agg(F.min(ts).alias("lo_")).select(F.lit("train").alias("split"), F.explode(back).alias("seed_time"))
    return stamps_frame(facts.sparkSession, [("val", split.t_val), ("test", split.t_test)]).unionByName(train)


def stamps_frame(spark: SparkSession, listed: list[tuple[str, datetime]]) -> DataFrame:
    return spark.createDataFrame([(s, t) for s, t in listed], "split string, seed_time timestamp_ntz")


def matching_stamps(facts: DataFrame, ts: str, first: datetime, stride: int, count: int, back: int, ahead: int) -> DataFrame:
    """Facts with the stamps whose window holds them, by arithmetic instead of a range join.

    Stamps are first + k * stride days, 0 <= k < count; a window is (stamp - back, stamp + ahead].  Each fact is
    repeated once per stamp that it matters to; times count to the microsecond, and a fact without one matters to none.
    """
    day = 86400 * 1000000
    at, step = micros(F.col(ts), first), F.lit(day * stride)
    ceil = lambda x: F.rint((x + F.pmod(-x, step)) / step).cast("bigint")  # noqa: E731  (whole numbers all through)
    low = F.greatest(ceil(at - day * ahead), F.lit(0)).cast("int")
    high = F.least(ceil(at + day * back) - 1, F.lit(count - 1)).cast("int")
    hit = facts.filter(F.col(ts).isNotNull()).withColumn("k_", F.when(low <= high, F.sequence(low, high))).filter("k_ is not null")
    return hit.withColumn("k_", F.explode("k_")).withColumn("seed_time", F.lit(first.isoformat(" ")).cast("timestamp_ntz") + F.make_dt_interval(days=F.col("k_") * stride)).drop("k_")


def at_stamps(facts: DataFrame, listed: list[tuple[str, datetime]], stride: int, back: int, ahead: int) -> DataFrame:
    """Facts (with ts) with split and seed_time of the stamps whose window (stamp - back, stamp + ahead] holds them.

    Training stamps and those that lie on their grid go by arithmetic, so a fact costs as many rows as it has stamps; the
    few others, at most the validation and test time, by a range join.
    """
    first = min(t for s, t in listed if s == "train")
    on = [(s, t) for s, t in listed if (t - first) % timedelta(days=stride) == timedelta(0)]
    off = [x for x in listed if x not in on]
    count = max((t - first).days for _, t in on) // stride + 1
    grid = matching_stamps(facts, "ts", first, stride, count, back, ahead)
    out = grid.join(F.broadcast(stamps_frame(facts.sparkSession, on)), "seed_time")
    if off:
        few = F.broadcast(stamps_frame(facts.sparkSession, off))
        t = F.col("seed_time")
        inside = (F.col("ts") > t - F.make_dt_interval(days=F.lit(back))) & (F.col("ts") <= t + F.make_dt_interval(days=F.lit(ahead)))
        out = out.unionByName(facts.join(few, inside))
    return out
