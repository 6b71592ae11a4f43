"""Tables written to the session's shared checkpoint folder, so that plans stay short and lost executors cost no lineage."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Where it is unset a temporary one is made, on one machine only (tests)."""
    context = spark.sparkContext
    if (found := context.getConf().get("spark.checkpoint.dir")) is not None:
        return found
    if context.getCheckpointDir() is None:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def materialised(df: DataFrame) -> DataFrame:
    """df, computed once and written to the shared folder."""
    folder(df.sparkSession)
    return df.checkpoint()
