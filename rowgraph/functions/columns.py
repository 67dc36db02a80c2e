"""Column builders used by tasks, samplers and features, and their SQL registration."""

from __future__ import annotations

from collections.abc import Callable
from datetime import datetime

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def days(n: int) -> Column:
    return F.expr(f"interval '{int(n)}' day")


def visible_at(ts: Column, t: Column) -> Column:
    """A row is visible at t where its time isn't later; a row without time always is."""
    return ts.isNull() | (ts <= t)


def in_future(ts: Column, t: Column, width: int) -> Column:
    """ts in (t, t + width days]."""
    return (ts > t) & (ts <= t + days(width))


def in_past(ts: Column, t: Column, width: int | None) -> Column:
    """ts in (t - width days, t]; without width, any time up to t."""
    return ts <= t if width is None else (ts > t - days(width)) & (ts <= t)


def draw(*parts: Column) -> Column:
    """md5 of the parts joined by bars: the same in every engine."""
    return F.md5(F.concat_ws("|", *(p.cast("string") for p in parts)))


def prefix_number(h: Column) -> Column:
    """The first 13 hex digits of a draw as a number."""
    return F.conv(F.substring(h, 1, 13), 16, 10).cast("bigint")


def hash_unit(h: Column) -> Column:
    """A draw as a number in (0, 1)."""
    return (prefix_number(h) + F.lit(0.5)) / F.lit(float(16**13))


def race_key(u: Column, w: Column) -> Column:
    """Key of the exponential race: the m smallest are a draw without replacement by weight."""
    return -F.log(u) / w


def recency_weight(ts: Column, t: Column, half_life: float) -> Column:
    """Weight halves with each half_life days of age; a row without time weighs 1."""
    age = F.datediff(t, ts).cast("double")
    return F.coalesce(F.exp(-F.lit(0.6931471805599453) * age / F.lit(float(half_life))), F.lit(1.0))


def anchor_weight(ts: Column, anchors: list[Column], width: float, floor: float = 1e-6) -> Column:
    """Weight by nearness to the closest of some moments."""
    parts = [F.exp(-F.abs(F.datediff(ts, a).cast("double")) / F.lit(float(width))) for a in anchors]
    return F.coalesce(F.greatest(F.lit(floor), *parts), F.lit(1.0))


# vectors as arrays


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def register_functions(spark: SparkSession) -> list[str]:
    """Registers visible_at, in_future and hash_unit as SQL functions and stamps_between as a table function."""
    spark.sql("create or replace temporary function visible_at(ts timestamp_ntz, t timestamp_ntz) returns boolean return ts is null or ts <= t")
    spark.sql("create or replace temporary function in_future(ts timestamp_ntz, t timestamp_ntz, n int) returns boolean return ts > t and ts <= t + make_dt_interval(n)")
    spark.sql(f"create or replace temporary function hash_unit(k string) returns double return (cast(conv(substr(md5(k), 1, 13), 16, 10) as bigint) + 0.5d) / {float(16**13)!r}d")
    spark.sql("create or replace temporary function race_key(u double, w double) returns double return -ln(u) / w")
    spark.udtf.register("stamps_between", stamps_between())
    return ["visible_at", "in_future", "hash_unit", "race_key", "stamps_between"]


def stamps_between() -> Callable:
    """Table function: stamps_between(start, stop, stride in days) as ISO dates."""
    from datetime import date, timedelta

    class Stamps:
        def eval(self, start: str, stop: str, stride: int):
            t, end = date.fromisoformat(start), date.fromisoformat(stop)
            while t <= end:
                yield (t.isoformat(),)
                t += timedelta(days=stride)

    return F.udtf(Stamps, returnType="stamp string")


def micros(ts: Column, since: datetime = datetime(1970, 1, 1)) -> Column:
    """Microseconds from a moment to a time without zone; no session's zone has a say in it."""
    passed = ts.cast("timestamp_ntz") - F.lit(since.isoformat(" ")).cast("timestamp_ntz")
    return (passed.cast("interval second").cast("decimal(20,6)") * 1000000).cast("bigint")


def nearest_second(ts: Column) -> Column:
    """Whole seconds since 1970, to the nearest, halves to even."""
    return F.rint(micros(ts) / 1e6).cast("bigint")
