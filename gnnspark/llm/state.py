"""Shared state of long jobs: reliable checkpoints in the folder that the cluster names."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, else the context's checkpoint folder.

    A temporary folder is taken only in local mode, where all tasks share it; a cluster that names no folder is an error.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = os.path.join(tempfile.gettempdir(), "checkpoints", "gnnspark")
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return named


def run_dir(spark: SparkSession, kind: str) -> str:
    """A fresh folder name below the shared one."""
    return f"{shared_dir(spark).rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, folder: str) -> None:
    """Delete a folder that nothing reads any more, on whatever file system it is."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def checkpointed(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and read it from there; its lineage ends here."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` evaluated once per row, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def map_in_arrow(df: DataFrame, func, schema, batch_bytes: int = 8 << 20) -> DataFrame:
    """``df.mapInArrow`` with Arrow batches of at most ``batch_bytes``: both sides of the pipe hold a few of them at a time.

    The bound is a runtime setting of the session; it is only ever lowered.
    """
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    now = conf.get(key).rstrip("b")
    if not now.isdigit() or int(now) > batch_bytes:
        conf.set(key, str(batch_bytes))
    return df.mapInArrow(func, schema)
