"""A folder that driver and executors share, for checkpoints of streams and cut lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


def scratch(spark: SparkSession, name: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or "file://" + tempfile.mkdtemp(prefix="sharetree-")
    return f"{base.rstrip('/')}/sharetree/{name}-{uuid.uuid4().hex[:12]}"
