"""Measures over (label, score) rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def running_sums(grouped: DataFrame, key: str, cols: list[str], parts: int = 64) -> DataFrame:
    """Inclusive running sums of ``cols`` in descending order of ``key`` without one task that holds all rows.

    Keys are cut at approximate quantiles; each range's totals are a few rows, and their sums are added to the running
    sums inside the ranges.
    """
    cuts = grouped.agg(F.percentile_approx(key, F.array(*(F.lit(i / parts) for i in range(1, parts))), 10000).alias("cuts_"))
    placed = grouped.crossJoin(F.broadcast(cuts)).withColumn("range_", F.aggregate("cuts_", F.lit(0), lambda s, x: s + (F.col(key) >= x).cast("int"))).drop("cuts_")
    totals = placed.groupBy("range_").agg(*(F.sum(c).alias(f"all_{c}") for c in cols))
    above = Window.orderBy(F.desc("range_")).rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("range_", *(F.coalesce(F.sum(f"all_{c}").over(above), F.lit(0)).alias(f"off_{c}") for c in cols))
    inside = Window.partitionBy("range_").orderBy(F.desc(key))
    summed = placed.join(F.broadcast(offsets), "range_")
    return summed.select(*grouped.columns, *((F.sum(c).over(inside) + F.col(f"off_{c}")).alias(f"cum_{c}") for c in cols))


def average_precision(df: DataFrame, y: str = "label", score: str = "score") -> DataFrame:
    """One row ``ap``: sum over distinct scores of the gain in recall times precision; tied scores are one threshold.

    Null where there is no positive.
    """
    grouped = df.groupBy(score).agg(F.count("*").alias("n"), F.sum(F.col(y).cast("bigint")).alias("p"))
    sums = running_sums(grouped.withColumnRenamed(score, "score_"), "score_", ["n", "p"])
    total = F.sum("p")
    return sums.agg(F.try_divide(F.sum(F.col("p") * F.col("cum_p") / F.col("cum_n")), total).alias("ap"))


def mean_abs_error(df: DataFrame, y: str = "label", y_hat: str = "y_hat") -> DataFrame:
    return df.agg((F.sum(F.abs(F.col(y) - F.col(y_hat)).cast("decimal(28,6)")).cast("double") / F.count("*")).alias("mae"))


def root_mean_square(df: DataFrame, y: str = "label", y_hat: str = "y_hat") -> DataFrame:
    d = (F.col(y) - F.col(y_hat)).cast("decimal(18,4)")
    return df.agg(F.sqrt(F.sum(d * d).cast("double") / F.count("*")).alias("rmse"))


def roc_auc(df: DataFrame, y: str = "label", score: str = "score") -> DataFrame:
    """Share of pairs in the right order, ties half: from ranks of score groups."""
    grouped = df.groupBy(F.col(score).alias("score_")).agg(F.sum(F.col(y).cast("bigint")).alias("p"), F.sum(1 - F.col(y).cast("bigint")).alias("q"))
    sums = running_sums(grouped, "score_", ["p", "q"])
    won = F.sum(F.col("q") * (F.col("cum_p") - F.col("p")) + F.col("p") * F.col("q") / F.lit(2.0))
    return sums.agg(F.try_divide(won, F.sum("p").cast("double") * F.sum("q")).alias("auc"))


def accuracy(df: DataFrame, y: str = "label", y_hat: str = "y_hat") -> DataFrame:
    return df.agg((F.count(F.when(F.col(y) == F.col(y_hat), 1)) / F.count("*")).alias("accuracy"))


def macro_f1(df: DataFrame, y: str = "label", y_hat: str = "y_hat") -> DataFrame:
    """Mean over true classes of the harmonic mean of precision and recall."""
    cells = df.groupBy(F.col(y).alias("a"), F.col(y_hat).alias("b")).count()
    true = cells.groupBy(F.col("a").alias("k")).agg(F.sum("count").alias("t"), F.sum(F.when(F.col("a") == F.col("b"), F.col("count")).otherwise(0)).alias("hit"))
    said = cells.groupBy(F.col("b").alias("k")).agg(F.sum("count").alias("s"))
    return true.join(said, "k", "left").agg(F.avg(2 * F.col("hit") / (F.col("t") + F.coalesce("s", F.lit(0)))).alias("macro_f1"))


def recall_at_k(ranked: DataFrame, truth: DataFrame, keys: list[str], dst: str, k: int) -> DataFrame:
    """ranked: keys, dst, score; truth: keys, dst.  Mean over sources of the share of true targets among the k best."""
    w = Window.partitionBy(*keys).orderBy(F.desc("score"), dst)
    top = ranked.withColumn("r_", F.row_number().over(w)).filter(F.col("r_") <= k).select(*keys, dst, F.lit(1).alias("hit"))
    per = truth.join(top, [*keys, dst], "left").groupBy(*keys).agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*")).alias("r"))
    return per.agg(F.avg("r").alias("recall"))


def map_at_k(ranked: DataFrame, truth: DataFrame, keys: list[str], dst: str, k: int) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(F.desc("score"), dst)
    top = ranked.withColumn("r_", F.row_number().over(w)).filter(F.col("r_") <= k)
    hits = top.join(truth.select(*keys, dst), [*keys, dst], "left_semi").withColumn("h_", F.row_number().over(Window.partitionBy(*keys).orderBy("r_")))
    per = hits.groupBy(*keys).agg(F.sum(F.col("h_") / F.col("r_")).alias("sum_"))
    n = truth.groupBy(*keys).agg(F.least(F.count("*"), F.lit(k)).alias("n_"))
    return n.join(per, keys, "left").agg(F.avg(F.coalesce("sum_", F.lit(0.0)) / F.col("n_")).alias("map"))

