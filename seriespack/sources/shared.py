"""A folder that the driver and the executors share: the cluster's checkpoint folder, or a temporary one in tests."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession

_own: list[str] = []


def fresh(spark: SparkSession, name: str) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _own:
            _own.append("file://" + tempfile.mkdtemp(prefix="seriespack-"))
        root = _own[0]
    return f"{root.rstrip('/')}/seriespack/{name}-{uuid.uuid4().hex}"
