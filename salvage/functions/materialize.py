"""Cutting lineage in the folder that the cluster shares, and spreading small scans."""

from __future__ import annotations

from pyspark.sql import DataFrame

from salvage.functions.scratch import shared_folder


def checkpoint(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the session's shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def spread(df: DataFrame) -> DataFrame:
    """``df`` over all cores if its scan has fewer splits than those; a table of many files is returned as it is.

    Goes before heavy work on texts: a file of one row group is otherwise read, and worked on, by one task.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df
