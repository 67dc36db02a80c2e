"""Task tables: seeds, labels mined from history, and their variants."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import Database
from ..functions.columns import draw, in_future, in_past, prefix_number
from .timeline import SplitSpec, at_stamps, stamp_list, stamps_frame

#: Stamps up to which every fact is held against every stamp.
FEW_STAMPS = 8


@dataclass(frozen=True)
class Label:
    """Aggregate of the facts in (t, t + delta]: sum, count, exists, absent, avg, max, nth or set of ``value``.

    "nth" is the value of the ``n``-th fact by time, equal times by value.  ``where`` filters facts; no fact gives 0.
    """

    agg: str = "count"
    value: Column | None = None
    where: Column | None = None
    n: int = 1

    def column(self, ahead: Column) -> Column:
        keep = ahead if self.where is None else ahead & self.where
        if self.agg == "sum":  # exact: money as decimals
            return F.coalesce(F.sum(F.when(keep, self.value.cast("decimal(18,2)"))), F.lit(0)).cast("double")
        if self.agg in ("avg", "max"):
            value = F.when(keep, self.value.cast("decimal(18,2)"))
            return F.coalesce(F.try_divide(F.sum(value).cast("double"), F.count(value)) if self.agg == "avg" else F.max(value), F.lit(0)).cast("double")
        if self.agg == "nth":
            # a window's facts of one entity; the smallest n would do, but arrays of them are short
            found = F.array_sort(F.collect_list(F.when(keep, F.struct(F.col("ts"), self.value.alias("v")))))
            return F.coalesce(F.get(found, F.lit(self.n - 1))["v"], F.lit(0)).cast("double")
        if self.agg == "set":
            return F.array_sort(F.collect_set(F.when(keep, self.value)))
        n = F.count(F.when(keep, 1))
        return {"count": n, "exists": (n > 0).cast("int"), "absent": (n == 0).cast("int")}[self.agg]


@dataclass(frozen=True)
class TaskSpec:
    """A temporal task on one entity.

    ``eligible``: "active" (a fact in the last ``look_back`` days), "ever" (any fact so far), "created" (its own time
    in the last ``look_back`` days) or "where" (all entities of which ``where`` is true, at every stamp).
    """

    name: str
    key: str
    delta: int
    label: Label
    eligible: str = "active"
    look_back: int | None = None
    stride: int | None = None
    min_history: int = 0
    kind: str = "regression"
    only: Column | None = None
    extra: dict[str, Label] = field(default_factory=dict)
    where: Column | None = None


def build_task_table(spec: TaskSpec, facts: DataFrame, split: SplitSpec, entities: DataFrame | None = None, allow_overrun: bool = False, listed: list[tuple] | None = None) -> DataFrame:
    """split, seed_time, key and label(s).

    ``facts`` has the key and ts.  Filter and label are read in one pass over the facts: each meets the stamps whose past
    or future window holds it, a few stamps by a range join, many of one stride by arithmetic, and flags are added up by
    entity and stamp.  ``listed`` replaces the stamps that the split and the spec give.  For "created", ``entities`` has the key and ts, and an entity without a fact in the
    window gets label 0.
    """
    split.check(spec.delta, allow_overrun)
    listed = listed or stamp_list(split, spec.delta, spec.stride, spec.min_history)
    table = F.broadcast(stamps_frame(facts.sparkSession, listed))
    if spec.only is not None:
        facts = facts.filter(spec.only)
    ts, t = F.col("ts"), F.col("seed_time")
    ahead = in_future(ts, t, spec.delta)
    labels = {"label": spec.label, **spec.extra}
    # a literal bound that reaches the scan, besides the bound by each stamp
    last = max(s for _, s in listed)
    near = facts.filter(ts <= F.lit(last).cast("timestamp_ntz") + F.make_dt_interval(days=F.lit(spec.delta)))
    if spec.eligible in ("created", "where"):
        met = entities.join(table, in_past(ts, t, spec.look_back)) if spec.eligible == "created" else entities.filter(spec.where).crossJoin(table)
        seeds = met.select("split", "seed_time", spec.key)
        found = near.join(table, ahead).groupBy("split", "seed_time", spec.key).agg(*(v.column(F.lit(True)).alias(k) for k, v in labels.items()))
        joined = seeds.join(found, ["split", "seed_time", spec.key], "left")
        zero = {"absent": 1}
        return joined.select("split", "seed_time", spec.key, *(F.coalesce(F.col(k), F.lit(zero.get(v.agg, 0))).cast(dict(found.dtypes)[k]).alias(k) for k, v in labels.items()))
    past = in_past(ts, t, spec.look_back if spec.eligible == "active" else None)
    if spec.eligible == "active" and len(listed) > FEW_STAMPS:
        rows = at_stamps(near, listed, spec.stride or spec.delta, spec.look_back, spec.delta)
    else:
        rows = near.join(table, past | ahead)
    out = rows.groupBy("split", "seed_time", spec.key).agg(F.count(F.when(past, 1)).alias("past_"), *(v.column(ahead).alias(k) for k, v in labels.items()))
    return out.filter("past_ > 0").drop("past_")


def task_from_sql(spark: SparkSession, sql: str, listed: list[tuple], delta: int) -> DataFrame:
    """A label query in the user's SQL, with :t and :delta, run for each stamp."""
    runs = [spark.sql(sql, args={"t": t, "delta": delta}).select(F.lit(s).alias("split"), F.lit(t).cast("timestamp_ntz").alias("seed_time"), "*") for s, t in listed]
    return reduce(DataFrame.unionByName, runs)


def link_positives(facts: DataFrame, src: str, dst: str, table: DataFrame, delta: int) -> DataFrame:
    """Distinct pairs of facts in the window of each stamp."""
    hit = facts.join(F.broadcast(table), in_future(F.col("ts"), F.col("seed_time"), delta))
    return hit.select("split", "seed_time", src, dst).distinct()


def link_negatives(positives: DataFrame, src: str, dst: str, n_dst: int, per_positive: int = 1, salt: str = "neg") -> DataFrame:
    """Targets drawn by md5 among keys 0 .. n_dst - 1 for each positive, without those that are positives."""
    drawn = positives.withColumn("j_", F.explode(F.sequence(F.lit(1), F.lit(per_positive))))
    h = draw(F.lit(salt), F.col(src), F.date_format("seed_time", "yyyy-MM-dd"), F.col(dst), F.col("j_"))
    drawn = drawn.select("split", "seed_time", src, F.pmod(prefix_number(h), F.lit(n_dst)).alias(dst)).distinct()
    return drawn.join(positives, ["split", "seed_time", src, dst], "left_anti")


def tuple_task(facts: DataFrame, keys: list[str], table: DataFrame, delta: int) -> DataFrame:
    """More than two keys: how often each combination occurs in the window."""
    hit = facts.join(F.broadcast(table), in_future(F.col("ts"), F.col("seed_time"), delta))
    return hit.groupBy("split", "seed_time", *keys).agg(F.count("*").alias("label"))


def static_split(key: Column) -> Column:
    """train, val or test for a static task, by md5 of the key."""
    n = F.pmod(prefix_number(draw(F.lit("split"), key)), F.lit(10))
    return F.when(n < 8, "train").when(n == 8, "val").otherwise("test")


def static_task(df: DataFrame, key: str, label: Column) -> DataFrame:
    return df.select(static_split(F.col(key)).alias("split"), key, label.alias("label"))


def describe(task: DataFrame) -> DataFrame:
    """Range, positive rate and size per split."""
    y = F.col("label").cast("double")
    return task.groupBy("split").agg(F.count("*").alias("n"), F.min(y).alias("lo"), F.max(y).alias("hi"), F.count(F.when(y > 0, 1)).alias("positives"))


def join_tasks(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """Several labels for shared seeds; a seed that only one task has keeps null for the other."""
    left, right = a.withColumnRenamed("label", "label_a"), b.withColumnRenamed("label", "label_b")
    return left.join(right, ["split", "seed_time", *keys], "outer")


def mine_tasks(facts: dict[str, tuple[str, str]], delta: int) -> list[TaskSpec]:
    """Label recipes that need no labels: for each fact table (its key and a number column) the count and sum of what comes next."""
    out = []
    for name, (key, value) in facts.items():
        out.append(TaskSpec(f"{name}_next_count", key, delta, Label("count"), look_back=delta))
        out.append(TaskSpec(f"{name}_next_sum", key, delta, Label("sum", F.col(value)), look_back=delta))
        out.append(TaskSpec(f"{name}_any_next", key, delta, Label("exists"), look_back=delta, kind="binary"))
    return out


def audit_leaks(rows: DataFrame, node_ts: str = "ts", seed_time: str = "seed_time", by: list[str] | None = None) -> DataFrame:
    """Numbers of rows newer than their seed, which should be 0."""
    return rows.groupBy(*(by or [])).agg(F.count("*").alias("n_rows"), F.count(F.when(F.col(node_ts) > F.col(seed_time), 1)).alias("n_leaks"))


def with_label(spec: TaskSpec, agg: str, kind: str) -> TaskSpec:
    return replace(spec, label=replace(spec.label, agg=agg), kind=kind)


Builder = Callable[[SparkSession, str], DataFrame]


@dataclass(frozen=True)
class Task:
    """A task table with its database: what a model may read, the rows of each split, and one way to be scored."""

    spec: TaskSpec
    table: DataFrame
    db: Database
    split: SplitSpec

    @property
    def inputs(self) -> Database:
        """The database without rows after the test time."""
        return self.db.visible(self.split.t_test)

    def rows(self, split: str) -> DataFrame:
        return self.table.filter(F.col("split") == split)

    @property
    def train(self) -> DataFrame:
        return self.rows("train")

    @property
    def val(self) -> DataFrame:
        return self.rows("val")

    @property
    def test(self) -> DataFrame:
        return self.rows("test")

    def score(self, predictions: DataFrame, model: str, split: str = "test") -> DataFrame:
        """task, model, metric, value of predictions (seed_time, key, and score or y_hat) for the rows of a split.

        A row without a prediction is an error, which a model that leaves out hard rows would otherwise hide.
        """
        from ..operators.board import evaluate

        said = "score" if self.spec.kind == "binary" else "y_hat"
        joined = self.rows(split).join(predictions.select("seed_time", self.spec.key, said), ["seed_time", self.spec.key], "left")
        missing = F.raise_error(F.lit("a row without a prediction")).cast("double")
        return evaluate(joined.withColumn(said, F.when(F.col(said).isNull(), missing).otherwise(F.col(said))), self.spec.kind, self.spec.name, model)
