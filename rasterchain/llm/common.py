"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import os
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space between words: blank and the control characters tab to carriage return.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the shared folder that the cluster names; one of our own only where none is set.

    Our own is a folder of the machine only if there is no other machine, else one in the shared warehouse.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        alone = re.fullmatch(r"local(\[[^\]]*\])?", sc.master)
        sc.setCheckpointDir(named or (os.path.join(tempfile.gettempdir(), "rasterchain-checkpoints") if alone else f"{spark.conf.get('spark.sql.warehouse.dir')}/_rasterchain_checkpoints"))


def checkpoint(df: DataFrame) -> DataFrame:
    """Writes df to the shared checkpoint folder, so that later steps survive lost executors."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def saved(df: DataFrame) -> DataFrame:
    """df as a table in the shared checkpoint folder, for rows too wide to be checkpointed as they are."""
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small_enough(df: DataFrame, max_rows: int) -> bool:
    """True if df, which should be materialised, has at most max_rows rows; reads no more than that."""
    return df.limit(max_rows + 1).count() <= max_rows


def broadcast_if_small(df: DataFrame, max_rows: int = 100_000) -> DataFrame:
    """Broadcast hint only behind a check of the row count; a plain shuffle join beyond it."""
    return F.broadcast(df) if small_enough(df, max_rows) else df


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))
