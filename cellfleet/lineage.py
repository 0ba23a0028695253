"""Lineage cuts in the folder that all executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, or the checkpoint folder that the session was given. On one machine alone (a local master) its
    own folder is shared by all and is made where none is set; on a cluster a missing one is an error."""
    there = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if there is None and spark.sparkContext.master.startswith("local"):
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="cellfleet-"))
        there = spark.sparkContext.getCheckpointDir()
    if there is None:
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return there


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written once: later steps neither recompute them nor lose them with an executor."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)
