"""Intermediate results that several branches of a plan read: made once, in the shared folder, so that they outlive lost executors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> None:
    """The session's own folder for checkpoints. In local mode, where it may be unset, one below the warehouse."""
    if spark.conf.get("spark.checkpoint.dir", None) is None and spark.sparkContext.getCheckpointDir() is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_checkpoints")


def shared_folder(spark: SparkSession) -> str:
    """The folder of checkpoints, which driver and executors share."""
    checkpoint_folder(spark)
    return spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()


def settled(df: DataFrame) -> DataFrame:
    """``df`` with its lineage cut: branches that read it don't make it again."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint()
