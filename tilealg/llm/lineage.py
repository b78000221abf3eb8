"""Cuts lineage in the shared folder that the session names; a machine-local one only for sessions on one machine."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> None:
    """Sees to it that a checkpoint folder is set: the session's own, else (tests, one machine) a temporary one.

    On a cluster that names none this is an error, as executors would not share a temporary folder.
    """
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder and not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="tilealg-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the checkpoint folder and read from there."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)
