"""Tables and files that one step writes and a later one reads.

Executors may be lost at any time, so whatever a later step needs is written under the folder named by
``spark.checkpoint.dir``, which every executor sees.
"""

from __future__ import annotations

import gc

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..sources.scratch import fresh_path, shared_dir

__all__ = ["clean_columns", "counted", "discard", "fresh_path", "kept_at", "shared_dir", "stage"]


def stage(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage and gives the planner true sizes."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


def counted(df: DataFrame, tag: str, which: Column | None = None) -> tuple[DataFrame, int]:
    """``stage``, and how many rows (those of ``which``) were written, counted on the way."""
    seen = Observation()
    out = stage(df.observe(seen, F.count(F.lit(1) if which is None else F.when(which, 1)).alias("n")), tag)
    return out, seen.get["n"]


def kept_at(df: DataFrame, staged: DataFrame) -> DataFrame:
    """``df``, which reads ``staged`` alone, to be discarded in its place."""
    df._staged_path = staged._staged_path
    return df


def clean_columns(docs: DataFrame, *names: str) -> DataFrame:
    """Only the named columns; one that is missing becomes a null string, and extra columns are dropped."""
    have = set(docs.columns)
    return docs.select(*(docs[n] if n in have else F.lit(None).cast("string").alias(n) for n in names))


def discard(*tables: DataFrame, shuffles: bool = False) -> None:
    """Deletes tables that ``stage`` wrote, once nothing that is still to run reads them.

    With ``shuffles`` the driver also collects its garbage, on which Spark removes shuffle files of plans that are gone.
    """
    for df in tables:
        path = getattr(df, "_staged_path", None)
        if path:
            spark = df.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    if shuffles and tables:
        gc.collect()
        tables[0].sparkSession._jvm.System.gc()
