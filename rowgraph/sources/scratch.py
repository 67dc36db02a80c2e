"""The folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession

_LOCAL = ""


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``, without a trailing slash.

    A local session without the setting (tests) gets a temporary folder of its own; a cluster without it is an error.
    """
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    if not spark.conf.get("spark.master", "").startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    global _LOCAL
    _LOCAL = _LOCAL or "file://" + tempfile.mkdtemp(prefix="rowgraph-shared-")
    return _LOCAL


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
