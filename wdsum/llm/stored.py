"""Intermediate tables in the shared folder that the cluster names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; a temporary one only where none is set, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        named = tempfile.mkdtemp(prefix="checkpoints-")
        spark.sparkContext.setCheckpointDir(named)
    return named


_written: list[str] = []


#: rows that are worth a task and a file of their own
TASK_ROWS = 50_000


def stored(df: DataFrame, rows: int | None = None) -> DataFrame:
    """``df`` written once and read back: computed once, lineage cut, survives lost executors.

    ``rows``: about how many are worked on, if known; few of them go to few files.
    The table stays until ``discard``: what reads it may run at any later time.
    """
    if rows is not None:
        df = df.coalesce(max(1, -(-rows // TASK_ROWS)))
    path = f"{folder(df.sparkSession).rstrip('/')}/table-{uuid.uuid4().hex}"
    _written.append(path)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def written() -> int:
    """How many tables this process has stored so far: a mark for ``discard``."""
    return len(_written)


def discard(spark: SparkSession, since: int = 0, keep: int = 0) -> None:
    """Deletes the tables that this process has stored after the mark ``since``, but the last ``keep``.

    Call it once their results are written.
    """
    jvm, end = spark._jvm, len(_written) - keep
    for name in _written[since:end]:
        path = jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    del _written[since : max(since, end)]
