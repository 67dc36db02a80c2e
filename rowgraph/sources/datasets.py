"""The given tables as linked databases."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import Database, LinkSpec, TableSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Time first, so that the lines up to a moment have the same places in their order whether later ones are there or not.
LINE_ORDER = ["l_shipdate", "l_partkey", "l_suppkey", "l_linenumber"]
LINES_PER_ORDER = 10000


def keyed_lines(lineitem: DataFrame, upto: datetime | None = None) -> DataFrame:
    """lineitem with its surrogate key ``l_id``: the order's key and the row's place in it, by time and the other keys.

    With ``upto`` only rows up to that time, by a filter that reaches the scan; their keys are those without it.  Attributes
    that are not asked for are not read.  An order with ``LINES_PER_ORDER`` lines or more is an error, as keys would meet.
    """
    if upto is not None:
        lineitem = lineitem.filter(F.col("l_shipdate") <= F.lit(upto).cast("timestamp_ntz"))
    seq = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER))
    keyed = lineitem.withColumn("seq_", seq)
    too_many = F.raise_error(F.concat(F.lit("too many lines in order "), F.col("l_orderkey").cast("string"))).cast("bigint")
    return keyed.withColumn("l_id", F.when(F.col("seq_") < LINES_PER_ORDER, F.col("l_orderkey") * LINES_PER_ORDER + F.col("seq_")).otherwise(too_many)).drop("seq_")


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per bought line: customer, part, time of the order, the part's price and the line's quantity."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    return (
        lines.join(orders, lines.l_orderkey == orders.o_orderkey)
        .join(part, lines.l_partkey == part.p_partkey)
        .select(F.col("o_custkey").alias("c_custkey"), "p_partkey", F.col("o_orderdate").alias("ts"), "p_retailprice", "l_quantity")
    )


def open_retail(spark: SparkSession, sf_dir: str, upto: datetime | None = None) -> Database:
    """All seven tables; with ``upto`` fact rows up to that time only, by filters that reach the scans."""
    t = lambda n: table(spark, sf_dir, n)
    orders = t("orders") if upto is None else t("orders").filter(F.col("o_orderdate") <= F.lit(upto).cast("timestamp_ntz"))
    return Database.of(
        [
            TableSpec("region", t("region"), "r_regionkey", None, "dimension"),
            TableSpec("nation", t("nation"), "n_nationkey", None, "dimension"),
            TableSpec("customer", t("customer"), "c_custkey", None, "dimension"),
            TableSpec("supplier", t("supplier"), "s_suppkey", None, "dimension"),
            TableSpec("part", t("part"), "p_partkey", None, "dimension"),
            TableSpec("orders", orders, "o_orderkey", "o_orderdate", "fact"),
            TableSpec("lineitem", keyed_lines(t("lineitem"), upto), "l_id", "l_shipdate", "fact"),
        ],
        [
            LinkSpec("nation", "n_regionkey", "region"),
            LinkSpec("customer", "c_nationkey", "nation"),
            LinkSpec("supplier", "s_nationkey", "nation"),
            LinkSpec("orders", "o_custkey", "customer"),
            LinkSpec("lineitem", "l_orderkey", "orders"),
            LinkSpec("lineitem", "l_partkey", "part"),
            LinkSpec("lineitem", "l_suppkey", "supplier"),
        ],
    )


def open_purchases(spark: SparkSession, sf_dir: str) -> Database:
    """Three tables: customer and part, and purchases that refer to both."""
    lines = keyed_lines(table(spark, sf_dir, "lineitem"))
    orders = table(spark, sf_dir, "orders")
    bought = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(
        F.col("l_id").alias("purchase_id"), "o_custkey", F.col("l_partkey").alias("b_partkey"), F.col("o_orderdate").alias("ts"), "l_quantity"
    )
    return Database.of(
        [TableSpec("customer", table(spark, sf_dir, "customer"), "c_custkey", None, "dimension"), TableSpec("part", table(spark, sf_dir, "part"), "p_partkey", None, "dimension"), TableSpec("purchase", bought, "purchase_id", "ts", "fact")],
        [LinkSpec("purchase", "o_custkey", "customer"), LinkSpec("purchase", "b_partkey", "part")],
    )


def open_activity(spark: SparkSession, sf_dir: str) -> Database:
    t = lambda n: table(spark, sf_dir, n)
    return Database.of(
        [TableSpec("region", t("region"), "r_regionkey"), TableSpec("nation", t("nation"), "n_nationkey"), TableSpec("customer", t("customer"), "c_custkey"), TableSpec("events", t("events"), "event_id", "ts", "fact")],
        [LinkSpec("nation", "n_regionkey", "region"), LinkSpec("customer", "c_nationkey", "nation"), LinkSpec("events", "user_id", "customer")],
    )


def open_corpus(spark: SparkSession, sf_dir: str) -> Database:
    """labels -> documents -> lang and source, which are tables made of their values; turns -> conversations."""
    docs = table(spark, sf_dir, "documents")
    # turns are numbered within 32 bits, so the two numbers side by side can't meet those of another conversation
    turns = table(spark, sf_dir, "conversations").withColumn("turn_id", F.shiftleft(F.col("conv_id"), 32) + F.col("turn"))
    return Database.of(
        [
            TableSpec("lang", docs.select("lang").distinct(), "lang"),
            TableSpec("source", docs.select("source").distinct(), "source"),
            TableSpec("documents", docs, "doc_id"),
            TableSpec("labels", table(spark, sf_dir, "labels").withColumnRenamed("doc_id", "label_doc"), "label_doc"),
            TableSpec("conversation", turns.select("conv_id").distinct(), "conv_id"),
            TableSpec("turns", turns.withColumnRenamed("conv_id", "t_conv"), "turn_id"),
        ],
        [LinkSpec("documents", "lang", "lang"), LinkSpec("documents", "source", "source"), LinkSpec("labels", "label_doc", "documents"), LinkSpec("turns", "t_conv", "conversation")],
    )
