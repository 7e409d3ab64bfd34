"""Places for files that all executors see."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path in the shared folder of the session; where none is set (tests), one of this machine."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir() or "file://" + tempfile.mkdtemp(prefix="shared-")
    return f"{root.rstrip('/')}/{what}-{uuid.uuid4().hex}"
