"""Folders for tables that a run writes."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


def new_folder(spark: SparkSession, name: str) -> str:
    """A new folder in the place all executors share: the session's ``spark.checkpoint.dir``. Where that is unset, a
    local run (tests) gets a temporary one, and a cluster an error, since its machines share no local folder."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = getattr(spark, "_own_folder", None)
        if base is None:
            base = spark._own_folder = "file://" + tempfile.mkdtemp()
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"
