"""Intermediate tables, written once to the folder that every executor shares, and joins that ask for their size.

The folder is the session's checkpoint directory (``spark.checkpoint.dir``).  Only a local session may go
without that setting; it then gets a temporary folder of its own.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of a table that may be broadcast.
BROADCAST_BYTES = 64 << 20


def shared_dir(spark: SparkSession) -> str:
    sc = spark.sparkContext
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    configured = sc.getConf().get("spark.checkpoint.dir", None)
    if configured is None:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        configured = tempfile.mkdtemp(prefix="tokenlink-")
        atexit.register(shutil.rmtree, configured, ignore_errors=True)  # what a local session wrote goes with it
    sc.setCheckpointDir(configured)
    return sc._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame) -> DataFrame:
    """Write ``df`` once and return a scan of what was written; a lost executor rereads, never recomputes."""
    path = f"{shared_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def is_short(written: DataFrame, row_bytes: Column) -> bool:
    """Whether a written table may be broadcast, by the sum of ``row_bytes``."""
    return (written.agg(F.sum(row_bytes).cast("long")).first()[0] or 0) <= BROADCAST_BYTES
