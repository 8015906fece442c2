"""Session helpers: shared work folder, lineage cuts, broadcast with a checked size."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F

BROADCAST_BYTES = 32 << 20


def work_folder(spark: SparkSession) -> str:
    """The folder that the session names in spark.checkpoint.dir; where none is set, a temporary one in local mode, an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            return held.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="hyperembed-")
        spark.sparkContext.setCheckpointDir(base)
    return base


def cut(df: DataFrame, label: str = "cut") -> DataFrame:
    """Write to the work folder and read back; iterated plans stay short and lost executors cost no recomputation."""
    path = f"{work_folder(df.sparkSession)}/graph-{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, row_bytes: int = 64, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Broadcast hint if a count proves that the rows fit in `limit` bytes."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df
