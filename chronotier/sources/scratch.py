"""Where queries that need a store or a stream keep their files."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import SparkSession


def folder(spark: SparkSession, name: str) -> str:
    """A new folder under spark.checkpoint.dir, which all executors and the driver
    reach; a temporary one on a local master that has none set."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        at = tempfile.mkdtemp(prefix="chronotier-")
        atexit.register(shutil.rmtree, at, ignore_errors=True)
        base = f"file://{at}"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
