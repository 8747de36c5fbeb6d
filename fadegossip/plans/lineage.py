"""Cutting long lineages through the shared checkpoint folder."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The folder the session names. On one machine (tests) a temporary one will do; on a cluster it must be named."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or os.path.join(tempfile.gettempdir(), "fadegossip-checkpoints"))


#: Rows up to which checked() broadcasts (some tens of bytes each).
BROADCAST_ROWS = 200_000


def checked(df: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """df, computed once, with a broadcast hint if it has few rows; otherwise Spark joins it by shuffle."""
    rows = cut(df)
    return F.broadcast(rows) if rows.count() <= most else rows


def cut(df: DataFrame) -> DataFrame:
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)
