"""Folders that driver and executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import SparkSession

from sparsecert.plans.relational import ensure_checkpoints


def shared_path(spark: SparkSession, name: str) -> str:
    """A new place below spark.checkpoint.dir, or below the folder that was set here because that is unset."""
    ensure_checkpoints(spark)
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
