"""Tables in the folder that all executors share: they cut lineage and survive the loss of any executor."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Where that is unset, a session whose tasks all run in this machine's one process (local mode, as in tests) takes a
    folder of this machine; on a cluster it is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = f"file://{tempfile.gettempdir()}/checkpoints/commlens-{os.getpid()}"
    return root.rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def _forget(spark: SparkSession, path: str) -> None:
    try:
        remove(spark, path)
    except Exception:  # noqa: BLE001  the session has ended; the folder goes with the application
        pass


def new_path(spark: SparkSession, kind: str = "table") -> str:
    """A path of its own in the shared folder, removed when the driver ends."""
    path = f"{shared_root(spark)}/{kind}-{uuid.uuid4().hex}"
    atexit.register(_forget, spark, path)
    return path


def written(df: DataFrame) -> DataFrame:
    path = new_path(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def drop(df: DataFrame | None) -> None:
    """Removes a table made by ``written``; anything else is left alone."""
    path = getattr(df, "_scratch_path", None)
    if path:
        remove(df.sparkSession, path)


def stamp(spark: SparkSession, paths: list[str]) -> tuple:
    """Path, size and time of change of files or folders, to tell whether tables made from them still hold."""
    out = []
    for p in paths:
        where = spark._jvm.org.apache.hadoop.fs.Path(p)
        status = where.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(where)
        out.append((p, status.getLen(), status.getModificationTime()))
    return tuple(out)
