"""Helpers shared by the operators: reading tables, shared checkpoints, Arrow blocks."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows of texts decoded together, and rows of an Arrow batch on its way to a worker: whole texts are long, and the
#: default of 10,000 rows would hold hundreds of MB for each task, outside the heap.
BLOCK_ROWS, BATCH_ROWS = 512, 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint(df: DataFrame) -> DataFrame:
    """Cut the lineage in the shared folder that the session names.

    Only a local session without any folder gets a folder of its own (tests).
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        shared = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if shared is None and not sc.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="salvage-checkpoint-"))
    return df.checkpoint(eager=True)


def short_batches(df: DataFrame) -> DataFrame:
    """``df``, after the session's Arrow batches (a setting of queries, not of the start) are limited to BATCH_ROWS."""
    conf, name = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(name, "10000")) <= BATCH_ROWS:
        conf.set(name, str(BATCH_ROWS))
    return df


def blocks(batches: Iterator[pa.RecordBatch], rows: int = BLOCK_ROWS) -> Iterator[pa.RecordBatch]:
    """The same rows in slices of at most ``rows`` rows."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder in whatever store Spark writes it to."""
    jvm = spark._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
