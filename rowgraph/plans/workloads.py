"""The workloads on the given tables: four of two databases, their literal widths, and the examples."""

from __future__ import annotations

from dataclasses import replace
from datetime import datetime

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import in_future
from ..sources.datasets import keyed_lines, purchases, table
from .tasks import Label, TaskSpec, build_task_table, static_task
from .timeline import SplitSpec, stamp_list, stamps_frame

D = datetime
RETAIL = SplitSpec(D(1999, 7, 1), D(2000, 7, 1), D(1995, 1, 1), D(2001, 8, 1))
RETAIL_730 = SplitSpec(D(1997, 7, 1), D(1999, 7, 1), D(1995, 1, 1), D(2001, 8, 1))
ACTIVITY = SplitSpec(D(2024, 1, 26), D(2024, 1, 28), D(2024, 1, 1), D(2024, 1, 30, 23, 59))


def value_spec(width: int = 365, min_history: int = 365) -> TaskSpec:
    return TaskSpec("customer_value", "c_custkey", width, Label("sum", F.col("p_retailprice")), look_back=width, min_history=min_history)


def churn_spec(width: int = 365, min_history: int = 365, delta: int | None = None, stride: int | None = None) -> TaskSpec:
    return TaskSpec("customer_churn", "c_custkey", delta or width, Label("absent"), look_back=width, min_history=min_history, stride=stride, kind="binary")


def customer_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_task_table(value_spec(), purchases(spark, sf_dir), RETAIL)


def customer_value_730(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_task_table(value_spec(730, 0), purchases(spark, sf_dir), RETAIL_730)


def customer_churn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_task_table(churn_spec(), purchases(spark, sf_dir), RETAIL)


def customer_churn_730(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_task_table(churn_spec(730, 0), purchases(spark, sf_dir), RETAIL_730)


CHURN_DAYS = (30, 90, 180)


def customer_churn_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No purchase in the next k days, for three k, with dense strides of 30 days over the same past.

    One pass: the stamps of the larger k are among those of the smallest, all labels are read off one window, and a row
    of the result belongs to the k whose windows end by the validation time.
    """
    narrow, *wider = CHURN_DAYS
    extra = {f"label_{k}": Label("absent", where=in_future(F.col("ts"), F.col("seed_time"), k)) for k in CHURN_DAYS}
    spec = replace(churn_spec(365, 365, delta=max(CHURN_DAYS), stride=30), extra=extra)
    listed = stamp_list(RETAIL, narrow, 30, 365)
    wide = build_task_table(spec, purchases(spark, sf_dir).select("c_custkey", "ts"), RETAIL, listed=listed)
    each = F.inline(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"label_{k}").alias("label")) for k in CHURN_DAYS)))
    ends = F.col("seed_time") + F.make_dt_interval(days=F.col("k"))
    rows = wide.select("split", "seed_time", "c_custkey", each)
    return rows.filter((F.col("split") != "train") | (ends <= F.lit(RETAIL.t_val).cast("timestamp_ntz"))).select("split", "seed_time", "c_custkey", "label", "k")


def user_engagement(spark: SparkSession, sf_dir: str) -> DataFrame:
    facts = table(spark, sf_dir, "events").filter("event_type = 'purchase'").select("user_id", "ts")
    return build_task_table(TaskSpec("user_engagement", "user_id", 2, Label("exists"), eligible="ever", kind="binary"), facts, ACTIVITY)


def order_attention(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").filter("l_returnflag = 'A'").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_shipdate").alias("ts"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").alias("ts"))
    spec = TaskSpec("order_attention", "o_orderkey", 182, Label("count"), eligible="created", look_back=365, min_history=365)
    return build_task_table(spec, lines, RETAIL, orders)


def spend_90d(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("ts"), "o_totalprice")
    spec = TaskSpec("spend_90d", "c_custkey", 90, Label("sum", F.col("o_totalprice")), look_back=365, min_history=365, stride=365)
    return build_task_table(spec, orders, RETAIL)


def part_sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines are dealt by part before they meet their stamps, so that each is moved once and not with every stamp."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("p_partkey"), F.col("l_shipdate").alias("ts"), "l_quantity").repartition("p_partkey")
    spec = TaskSpec("part_sales", "p_partkey", 182, Label("sum", F.col("l_quantity")), look_back=365, min_history=365)
    return build_task_table(spec, lines, RETAIL)


def static_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return static_task(table(spark, sf_dir, "labels"), "doc_id", F.col("quality"))


def static_toxic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return static_task(table(spark, sf_dir, "labels"), "doc_id", F.col("toxic"))


def multilabel_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    """label: an array of 0 and 1, quality and toxic."""
    return static_task(table(spark, sf_dir, "labels"), "doc_id", F.array(F.col("quality").cast("int"), F.col("toxic").cast("int")))


def multiclass_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return static_task(table(spark, sf_dir, "embeddings"), "vec_id", F.col("label"))


def static_impute_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return static_task(table(spark, sf_dir, "orders"), "o_orderkey", F.col("o_orderpriority"))


def multiclass_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most frequent event type of a user in the next two days; ties by name, users without an event are left out."""
    stamps_ = F.broadcast(stamps_frame(spark, stamp_list(ACTIVITY, 2)))
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    n = e.join(stamps_, in_future(F.col("ts"), F.col("seed_time"), 2)).groupBy("split", "seed_time", "user_id", "event_type").count()
    best = F.min(F.struct((-F.col("count")).alias("n"), F.col("event_type").alias("label")))
    return n.groupBy("split", "seed_time", "user_id").agg(best.alias("b")).select("split", "seed_time", "user_id", F.col("b.label").alias("label"))


def lines_with_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed_lines(table(spark, sf_dir, "lineitem"))
