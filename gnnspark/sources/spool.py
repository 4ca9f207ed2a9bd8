"""Tables of a run in the shared folder: they end a plan's lineage and survive lost executors."""

from __future__ import annotations

import atexit
import gc
import os
import posixpath
import shutil
import tempfile
import uuid

import numpy as np
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, kind: str) -> str:
    """A fresh folder below the shared one; in local mode, where all tasks share it, below the temporary folder if none is named."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = os.path.join(tempfile.gettempdir(), "checkpoints", "gnnspark")
    where = f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"
    _made.append(where)
    return where


_made: list[str] = []


@atexit.register
def _clean() -> None:
    """At the end of the driver its folders go, where they are local; elsewhere :func:`remove` or the store's own expiry deletes them."""
    for where in _made:
        shutil.rmtree(where.removeprefix("file:"), ignore_errors=True)


def remove(spark: SparkSession, folder: str) -> None:
    """Delete a folder that nothing reads any more, on whatever file system it is."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def let_go(spark: SparkSession) -> None:
    """Have the driver collect plans that nothing refers to any more: Spark deletes their shuffle files then, which it would otherwise do at its half-hourly collection."""
    gc.collect()
    spark._jvm.System.gc()


class Spool:
    """Tables of one run below one folder, so that all of them can go at once."""

    def __init__(self, spark: SparkSession):
        self.spark, self.folder, self.n = spark, scratch(spark, "spool"), 0

    def __call__(self, df: DataFrame) -> DataFrame:
        self.n += 1
        where = f"{self.folder}/{uuid.uuid4().hex}"
        df.write.parquet(where)
        return self.spark.read.schema(df.schema).parquet(where)

    def close(self) -> None:
        remove(self.spark, self.folder)


def spool(df: DataFrame) -> DataFrame:
    """Write ``df`` once as Parquet and read it from there. Plans over it stay small, however many steps made it."""
    where = scratch(df.sparkSession, "spool")
    df.write.parquet(where)
    return df.sparkSession.read.schema(df.schema).parquet(where)


def store(folder: str) -> tuple[fs.FileSystem, str]:
    """The file system of a folder, and its path there."""
    return fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else f"file://{posixpath.abspath(folder)}")


def piece(folder: str, name: str, kind: str, n: int, at: int = 0) -> np.ndarray:
    """``n`` values of a file from byte ``at``."""
    where, path = store(folder)
    size = np.dtype(kind).itemsize
    if n == 0:
        return np.zeros(0, kind)
    if isinstance(where, fs.LocalFileSystem):
        return np.memmap(f"{path}/{name}", kind, "r", at, (n,))
    with where.open_input_file(f"{path}/{name}") as f:
        return np.frombuffer(f.read_at(n * size, at), kind)


def put(folder: str, *parts: np.ndarray) -> str:
    """Arrays one after another in a new file of the folder; its name."""
    where, path = store(folder)
    where.create_dir(path, recursive=True)
    name = uuid.uuid4().hex
    with where.open_output_stream(f"{path}/{name}") as f:
        for p in parts:
            f.write(np.ascontiguousarray(p).tobytes())
    return name
