"""One way to score every model of a task, and a table of results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import metrics

#: Metric by kind of task.
METRIC = {"binary": "ap", "regression": "mae", "multiclass": "accuracy"}


def evaluate(pred: DataFrame, kind: str, task: str, model: str) -> DataFrame:
    """task, model, metric, value of predictions with label and score (binary) or y_hat."""
    name = METRIC[kind]
    made = {"ap": metrics.average_precision, "mae": metrics.mean_abs_error, "accuracy": metrics.accuracy}[name](pred)
    return made.select(F.lit(task).alias("task"), F.lit(model).alias("model"), F.lit(name).alias("metric"), F.col(name).alias("value"))


def append(row: DataFrame, path: str, seed: int = 0) -> None:
    row.withColumn("seed", F.lit(seed)).coalesce(1).write.mode("append").parquet(path)


def show(spark, path: str) -> DataFrame:
    """Mean and number of runs by task and model, best first (errors: smallest first)."""
    rows = spark.read.parquet(path).groupBy("task", "metric", "model").agg(F.avg("value").alias("value"), F.count("*").alias("runs"))
    return rows.orderBy("task", F.when(F.col("metric") == "mae", F.col("value")).otherwise(-F.col("value")))
