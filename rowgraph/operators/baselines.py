"""Features made by hand, one flat table, boosted trees, and controls."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import in_past


def recent_features(task: DataFrame, facts: DataFrame, key: str, value: str, widths: tuple[int, ...] = (7, 30, 90, 365), stamps: DataFrame | None = None) -> DataFrame:
    """Count and sum of an entity's facts over the last w days as of each seed time, for each w.

    Facts meet the stamps (a few rows) first, then one aggregate per (stamp, entity) holds all widths.  ``stamps`` (split,
    seed_time) are those of the task's split; without them they are read from the task, which is then computed twice.
    """
    stamps = task.select("split", "seed_time").distinct() if stamps is None else stamps
    hit = facts.join(stamps, in_past(F.col("ts"), F.col("seed_time"), max(widths)))
    cols: list[Column] = []
    for w in widths:
        inside = in_past(F.col("ts"), F.col("seed_time"), w)
        cols += [F.count(F.when(inside, 1)).alias(f"n_{w}"), F.coalesce(F.sum(F.when(inside, F.col(value).cast("decimal(18,2)"))), F.lit(0)).cast("double").alias(f"sum_{w}")]
    made = hit.groupBy("split", "seed_time", key).agg(*cols)
    names = [f"{p}_{w}" for w in widths for p in ("n", "sum")]
    return task.join(made, ["split", "seed_time", key], "left").select("split", "seed_time", key, *(F.coalesce(F.col(n), F.lit(0)).alias(n) for n in names))


def weekday_features(task: DataFrame, facts: DataFrame, key: str, value: str, width: int = 365, stamps: DataFrame | None = None) -> DataFrame:
    """Count and sum per weekday (1 is Sunday) over the last ``width`` days."""
    stamps = task.select("split", "seed_time").distinct() if stamps is None else stamps
    hit = facts.join(stamps, in_past(F.col("ts"), F.col("seed_time"), width))
    cols: list[Column] = []
    for d in range(1, 8):
        on = F.dayofweek("ts") == d
        cols += [F.count(F.when(on, 1)).alias(f"n_d{d}"), F.coalesce(F.sum(F.when(on, F.col(value).cast("decimal(18,2)"))), F.lit(0)).cast("double").alias(f"sum_d{d}")]
    made = hit.groupBy("split", "seed_time", key).agg(*cols)
    names = [f"{p}_d{d}" for d in range(1, 8) for p in ("n", "sum")]
    return task.join(made, ["split", "seed_time", key], "left").select("split", "seed_time", key, *(F.coalesce(F.col(n), F.lit(0)).alias(n) for n in names))


def flat_table(task: DataFrame, entity: DataFrame, key: str, attrs: list[str], *features: DataFrame) -> DataFrame:
    """Label, entity attributes and features side by side."""
    out = task.join(entity.select(key, *attrs), key, "left")
    for f in features:
        out = out.join(f, ["split", "seed_time", key], "left")
    return out


def fit_boosted(flat: DataFrame, label: str, kind: str, inputs: list[str], categories: tuple[str, ...] = (), trees: int = 20, depth: int = 4):
    """Gradient-boosted trees of the ML library on the train rows; returns the fitted pipeline."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import GBTClassifier
    from pyspark.ml.feature import StringIndexer, VectorAssembler
    from pyspark.ml.regression import GBTRegressor

    indexers = [StringIndexer(inputCol=c, outputCol=f"{c}_i", handleInvalid="keep") for c in categories]
    assemble = VectorAssembler(inputCols=[*inputs, *(f"{c}_i" for c in categories)], outputCol="features", handleInvalid="keep")
    model = GBTClassifier if kind == "binary" else GBTRegressor
    trees_ = model(labelCol=label, featuresCol="features", maxIter=trees, maxDepth=depth, seed=1)
    return Pipeline(stages=[*indexers, assemble, trees_]).fit(flat.filter("split = 'train'"))


def boosted_scores(fitted, flat: DataFrame, kind: str) -> DataFrame:
    """The rows with a column ``score``."""
    from pyspark.ml.functions import vector_to_array

    out = fitted.transform(flat)
    return out.withColumn("score", vector_to_array("probability")[1] if kind == "binary" else F.col("prediction"))


def constant(task: DataFrame, kind: str = "median") -> DataFrame:
    """Every row with y_hat, the mean or (lower) median of the train labels: one number."""
    train = task.filter("split = 'train'")
    y = F.col("label").cast("double")
    value = train.agg((F.sum(y.cast("decimal(28,6)")).cast("double") / F.count("*") if kind == "mean" else F.percentile(y, 0.5)).alias("y_hat"))
    return task.crossJoin(F.broadcast(value))


def persistence(task: DataFrame, facts: DataFrame, key: str, value: Column, width: int, stamps: DataFrame | None = None) -> DataFrame:
    """y_hat is the same aggregate over the window before the seed time."""
    stamps = task.select("split", "seed_time").distinct() if stamps is None else stamps
    past = facts.join(stamps, in_past(F.col("ts"), F.col("seed_time"), width)).groupBy("split", "seed_time", key).agg(F.sum(value.cast("decimal(18,2)")).cast("double").alias("y_hat"))
    return task.join(past, ["split", "seed_time", key], "left").withColumn("y_hat", F.coalesce("y_hat", F.lit(0.0)))
