"""Folders for what a query writes and reads back."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The session's shared folder. A local session without one gets a folder of its own, deleted when Python ends."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared is None:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        shared = tempfile.mkdtemp(prefix="salvage-")
        atexit.register(shutil.rmtree, shared, ignore_errors=True)
    return shared


def scratch(spark: SparkSession, name: str) -> str:
    """The name of a new folder inside the shared one."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
