"""Cutting lineage between rounds, in the folder that all executors share."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset and the session runs on
    one machine, one of our own.  A cluster must name one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
    return (named or "file://" + os.path.join(tempfile.gettempdir(), "polyprov-checkpoints")).rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint ``df`` in ``spark.checkpoint.dir`` (a folder of our own only if unset)."""
    spark = df.sparkSession
    if spark.conf.get("spark.checkpoint.dir", None) is None and spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)
