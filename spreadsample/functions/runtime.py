"""Durable intermediate results in the folder that the whole cluster shares."""

from __future__ import annotations

import tempfile
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a few narrow columns that a broadcast may hold.
BROADCAST_ROWS = 200_000
#: Jobs that an experiment runs side by side.
AT_ONCE = 4


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a temporary folder only where that is unset, as on one machine."""
    jvm_context = spark.sparkContext._jsc.sc()
    if jvm_context.getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="spread-"))
    return jvm_context.getCheckpointDir().get()


def durable(df: DataFrame) -> DataFrame:
    shared_folder(df.sparkSession)
    return df.checkpoint()


def parked(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the shared folder: for rows that are scanned often, and then mostly not all columns."""
    path = new_path(df.sparkSession, "parked")
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def together(*makers) -> list:
    """The results of independent functions, run at once: a job of one task leaves the other cores to the rest. The first error is raised."""
    ours = inheritable_thread_target(SparkSession.active())
    with ThreadPoolExecutor(max(1, min(AT_ONCE, len(makers)))) as pool:
        return [f.result() for f in [pool.submit(ours(m)) for m in makers]]


def new_path(spark: SparkSession, kind: str) -> str:
    return f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"


def bounded(df: DataFrame, rows: int) -> DataFrame:
    """df, of at most `rows` rows, marked for a broadcast if that many may be broadcast; else left to the join's own way."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df
