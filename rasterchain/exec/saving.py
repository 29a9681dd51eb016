"""Where results between rounds are written."""

from __future__ import annotations

import os
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the shared folder that the cluster names; one of our own only where none is set.

    Our own is a folder of the machine only if there is no other machine, else one in the shared warehouse.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        alone = re.fullmatch(r"local(\[[^\]]*\])?", sc.master)
        own = os.path.join(tempfile.gettempdir(), "rasterchain-checkpoints") if alone else f"{spark.conf.get('spark.sql.warehouse.dir')}/_rasterchain_checkpoints"
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or own)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder of its own within the shared one."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame) -> DataFrame:
    """df as written to the shared checkpoint folder, so that plans do not grow and lost executors cost one round at most."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def small_enough(df: DataFrame, max_rows: int = 100_000) -> bool:
    """Whether df has at most so many rows; reads no more than that."""
    return df.limit(max_rows + 1).count() <= max_rows
