"""Intermediate tables in the folder that driver and executors share.

A hop's rows are read by the next hop, the commit and the labels. Written and read again they cost one
pass, survive lost executors, and keep plans short: a cached frame still drags its whole logical plan
through every later analysis, which grows exponentially over hops and batches.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a temporary folder only where none is set on a local master (tests)."""
    set_by_user = spark.conf.get("spark.checkpoint.dir", None)
    if set_by_user:
        return set_by_user.rstrip("/")
    current = spark.sparkContext.getCheckpointDir()
    if not current:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        current = spark.sparkContext.getCheckpointDir()
    return str(current).rstrip("/")


def settled(df: DataFrame, what: str = "step") -> DataFrame:
    """The rows of ``df`` as a table in the shared folder."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    table._written_at = path
    return table


#: tables of at most so many rows travel through the driver instead of a file (a batch of updates, not a graph)
LOCAL_ROWS = 20_000


def settled_batch(df: DataFrame, rows: int | None) -> DataFrame:
    """Like :func:`settled`; a table known to have at most ``rows`` <= LOCAL_ROWS rows becomes a local relation."""
    if rows is None or rows > LOCAL_ROWS:
        return settled(df)
    return df.sparkSession.createDataFrame(df.toArrow(), df.schema)


def forget(*tables: DataFrame) -> None:
    """Delete tables made by :func:`settled` that nothing reads any more."""
    for table in tables:
        path = getattr(table, "_written_at", None)
        if path is None:
            continue
        target = table.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(table.sparkSession._jsc.hadoopConfiguration()).delete(target, True)
