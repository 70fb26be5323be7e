"""Cutting lineage in the folder that all executors share, and broadcasts of checked size."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SMALL_ROWS = 500_000


def checkpointed(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in spark.checkpoint.dir; a folder of our own only where that is unset in local mode, as in tests."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        place = spark.conf.get("spark.checkpoint.dir", None)
        if place is None and not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(place or os.path.join(tempfile.gettempdir(), "edgeloc-checkpoints"))
    return df.checkpoint()


def small(df: DataFrame, most: int = SMALL_ROWS) -> DataFrame:
    """df marked for broadcast if it has at most `most` rows, else as it is. For frames of a few short columns that are read several times."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df
