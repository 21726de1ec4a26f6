"""Cutting the lineage of loops with reliable checkpoints in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint: it survives lost executors."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint(eager=True)


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see: ``spark.checkpoint.dir``.  On one machine (``local[n]``) one of our own where it is unset."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors see")
        at = f"file:///tmp/checkpoints/{spark.sparkContext.applicationId}"
    return at.rstrip("/")


def small(df: DataFrame, most: int = 500_000) -> DataFrame:
    """``df`` with a broadcast hint where it has ``most`` narrow rows at most (counted), else as it is."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df
