"""Pieces that the operators share: Arrow batch mapping, scratch tables, bounded labelled samples."""

from __future__ import annotations

import atexit
import gc
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the separators of words in every contract.
SPACE = b" \t\n\r\x0b\x0c"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def limit_batches(spark: SparkSession, rows: int = 2500, size: str = "8m") -> None:
    """Arrow batches of so many rows and bytes at most, unless the session sets its own: Spark's default of 10,000 rows lets one
    batch of long texts take tens of megabytes off the heap in each task."""
    for key, value, default in (("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows), "10000"), ("spark.sql.execution.arrow.maxBytesPerBatch", size, None)):
        now = spark.conf.get(key, None)
        if now is None or default is None or now == default:
            spark.conf.set(key, value)


def slices(batch: pa.RecordBatch, column: str, rows: int = 1024, size: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of so many rows and bytes of a text column at most, but for single longer texts; they bound a step's memory."""
    length = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    at = 0
    while at < batch.num_rows:
        n = max(1, int(np.searchsorted(np.cumsum(length[at : at + rows]), size, "right")))
        yield batch.slice(at, n)
        at += n


def map_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str, text: str = "text") -> DataFrame:
    """Maps slices of Arrow batches, cut by the text column's bytes. ``make`` runs once per task, so that models load on the executor; it returns the batch function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            for part in slices(batch, text):
                yield step(part)

    limit_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


_holder: tuple[str, Callable[[], None]] | None = None


def claim(owner: str, release: Callable[[], None]) -> None:
    """Says that ``owner`` now keeps a store in this worker process; the store of the operator before it is released first, so
    that workers which serve several operators in turn hold one store at a time."""
    global _holder
    if _holder and _holder[0] != owner:
        _holder[1]()
        gc.collect()
        pa.default_memory_pool().release_unused()
    _holder = (owner, release)


def column_bytes(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """UTF-8 values of a string column; null gives an empty value."""
    return [x or b"" for x in batch.column(name).cast(pa.binary()).to_pylist()]


def column_text(batch: pa.RecordBatch, name: str) -> list[str]:
    return [x or "" for x in batch.column(name).to_pylist()]


def scratch_root(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Where that is unset, a session whose tasks all run in this machine's one
    process (local mode, as in tests) takes a folder of this machine; on a cluster it is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = f"file://{tempfile.gettempdir()}/checkpoints/commlens-{os.getpid()}"
    return root.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


#: The share of its greatest heap from which a driver of many queries collects its garbage between two of them.
HEAP_SHARE = 0.5


class Scratch:
    """Tables written to the shared folder to cut lineage: they survive the loss of any executor, and
    a task that runs again reads the same rows. Intermediate tables go with ``drop``, the rest when
    the driver ends. With ``tidy``, what finished queries hold is released after a table where the driver's heap has grown to HEAP_SHARE."""

    def __init__(self, spark: SparkSession, tidy: bool = False) -> None:
        self.spark = spark
        self.tidy = tidy
        self.paths: list[str] = []
        atexit.register(self._end)

    def table(self, df: DataFrame) -> DataFrame:
        path = f"{scratch_root(self.spark)}/scratch-{uuid.uuid4().hex}"
        df.write.parquet(path)
        self.paths.append(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        if self.tidy:
            heap = self.spark._jvm.java.lang.Runtime.getRuntime()
            if heap.totalMemory() >= HEAP_SHARE * heap.maxMemory():
                self.release()
        return out

    def drop(self, df: DataFrame) -> None:
        path = df._scratch_path
        _remove(self.spark, path)
        self.paths.remove(path)

    def release(self) -> None:
        """Lets Spark remove the shuffle files, broadcasts and compiled code of queries that are done: it does so only when the driver collects its garbage."""
        gc.collect()
        self.spark._jvm.System.gc()

    def _end(self) -> None:
        try:
            for path in self.paths:
                _remove(self.spark, path)
        except Exception:  # noqa: BLE001  the session has ended; the folder goes with the application
            pass


def crc_of_id(column: str = "doc_id") -> Column:
    return F.crc32(F.col(column).cast("string").cast("binary"))


def bounded_sample(df: DataFrame, key: str, size: int, strata: str) -> DataFrame:
    """At most ``size`` rows of each value of ``strata`` (a few values), the first in the order of a hash
    of ``key``. One count fixes a hash threshold, so that only about that many rows are sorted."""
    top = 1 << 30
    spot = F.pmod(F.xxhash64(F.col(key), F.lit(7)), F.lit(top))
    counts = {r[0]: r[1] for r in df.groupBy(strata).count().collect()}
    parts = []
    for value, n in sorted(counts.items(), key=str):
        if value is None:
            continue
        limit = min(top, int(top * 1.3 * size / n) + 1)
        parts.append(df.where((F.col(strata) == F.lit(value)) & (spot < limit)).orderBy(spot, key).limit(size))
    out = parts[0] if parts else df.limit(0)
    for part in parts[1:]:
        out = out.unionByName(part)
    return out
