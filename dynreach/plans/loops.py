"""Cutting lineage in loops, through the folder that all executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="dynreach-"))  # one machine


def cut(df: DataFrame) -> DataFrame:
    """df written to the shared checkpoint folder; plans above it are small again."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(True)


def fits(conf, *tables: DataFrame) -> bool:
    """Whether all the tables together have at most conf.local_rows rows; no more than that are counted."""
    left = conf.local_rows
    for table in tables:
        left -= table.limit(left + 1).count()
        if left < 0:
            return False
    return True


def empty(df: DataFrame) -> bool:
    return df.limit(1).count() == 0


def hinted(df: DataFrame, conf=DEFAULT) -> DataFrame:
    """df, to be broadcast if it has at most conf.broadcast_rows rows; no more than that are counted."""
    return F.broadcast(df) if df.limit(conf.broadcast_rows + 1).count() <= conf.broadcast_rows else df
