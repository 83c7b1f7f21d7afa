"""A folder that the driver and all executors see."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path in the session's checkpoint folder; in a temporary one only where none is set, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        named = tempfile.mkdtemp(prefix="checkpoints-")
        spark.sparkContext.setCheckpointDir(named)
    return f"{named.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def kept(df: DataFrame, name: str = "kept") -> DataFrame:
    """``df`` written once and read back: worked out once, however often it is used."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: rows of (stream, register) or (stream) that are broadcast at most
BROADCAST_ROWS = 1 << 18


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame | None:
    """``df``, worked out and to be broadcast, or None if it has more than ``rows`` rows."""
    df = kept(df)
    return F.broadcast(df) if df.count() <= rows else None
