"""What the operators share: reading tables, folders that all executors see, bounded collecting."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where that is unset (tests), a folder of this machine, once per session."""
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not folder:
        folder = getattr(sc, "_own_checkpoint_dir", None)
        if folder is None:
            folder = sc._own_checkpoint_dir = "/tmp/checkpoints/seqentropy"
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(folder)
    return folder


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str = "step") -> DataFrame:
    """Writes the rows to the shared folder and reads them again: a plan of one scan that outlives executors.

    Rows are the same at every later read, whatever cores there are; small files are read several to a task.
    """
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def wrapped(df: DataFrame, name: str = "whole") -> DataFrame:
    """All columns as one struct, so that columns added beside it can't clash with any of theirs."""
    return df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias(name))
