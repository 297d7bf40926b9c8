"""What a session shares between driver and executors."""

from __future__ import annotations

import functools
import tempfile
import uuid

from pyspark.sql import SparkSession


@functools.cache
def _own_dir(application: str) -> str:
    return tempfile.mkdtemp(prefix="trieaccess-")


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; one of our own only where it is unset, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    return (found or f"file://{_own_dir(spark.sparkContext.applicationId)}").rstrip("/")


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/trieaccess-{tag}-{uuid.uuid4().hex[:12]}"
