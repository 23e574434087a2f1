"""Cutting the lineage of iterations: rows go to the shared checkpoint folder and survive the loss of any executor."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import DataFrame, SparkSession


def prepare(spark: SparkSession) -> None:
    """Uses the folder that the session names; only a local master, whose executors are the driver, may do without one."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="tierdraw-state-"))


def cut(df: DataFrame) -> DataFrame:
    prepare(df.sparkSession)
    return df.checkpoint(eager=True)
