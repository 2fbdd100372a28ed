"""Tables that several queries of a session share: written once to the shared folder, then read."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from salvage.functions.scratch import scratch

_WRITTEN: dict[tuple, str] = {}
_SEEN: dict[tuple, tuple[float, tuple]] = {}
#: One lock a stage: threads that need the same one wait for its first builder.
_LOCKS: dict[tuple, threading.Lock] = {}
#: Seconds for which the files of an input are taken not to change.
FRESH = 60.0
#: The tables whose files are part of a stage's identity.
INPUTS = ("documents", "labels", "benchmark")


def _identity(spark: SparkSession, sf_dir: str) -> tuple:
    """What the input files are: a checksum of their names, sizes and times. Contents are not read."""
    place = (spark.sparkContext.applicationId, sf_dir)
    if place in _SEEN and time.monotonic() - _SEEN[place][0] < FRESH:
        return _SEEN[place][1]
    marks = []
    for name in INPUTS:
        files = spark.read.format("binaryFile").option("recursiveFileLookup", True).load(f"{sf_dir}/{name}.parquet")
        marks.append(files.agg(F.sum(F.xxhash64("path", "length", "modificationTime").cast("decimal(38,0)"))).first()[0])
    _SEEN[place] = (time.monotonic(), (*place, *marks))
    return _SEEN[place][1]


class Stages:
    """The written tables of one session and one input."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf, self.key = spark, sf_dir, _identity(spark, sf_dir)

    def table(self, name: str, build: Callable[[], DataFrame]) -> DataFrame:
        """The rows of ``build()``. Only its first use in a session computes and writes them."""
        key = (*self.key, name)
        with _LOCKS.setdefault(key, threading.Lock()):
            if key not in _WRITTEN:
                path = scratch(self.spark, f"stage-{name}")
                build().write.parquet(path)
                _WRITTEN[key] = path
        return self.spark.read.parquet(_WRITTEN[key])
