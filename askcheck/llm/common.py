"""What the operators of this subpackage share: inputs, scratch space, Arrow slices."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's ``spark.checkpoint.dir``.

    Only a session that runs in one process (tests, a laptop) may name none: a
    local folder is set there, while on a cluster other machines would miss its files.
    """
    sc = spark.sparkContext
    set_to = spark.conf.get("spark.checkpoint.dir", None)
    if sc.getCheckpointDir() is None:
        if set_to is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(set_to or tempfile.mkdtemp(prefix="askcheck-"))
    return set_to or sc.getCheckpointDir()


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path for a table that a job writes and a later one reads back."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a scratch table on whatever file system it is (by Spark's own handle to it, a private one)."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder, without its lineage."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def partitions_of(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_or_empty(col: str) -> Column:
    return F.coalesce(F.col(col).cast("string"), F.lit(""))


#: What operators keep in a Python worker from task to task, each with how to drop it.
_KEPT: list = []


def kept_by_worker(cached):
    """Mark a cached function whose values stay in a worker until another operator's task starts there."""
    _KEPT.append(cached)
    return cached


def lean_worker(*keep) -> None:
    """Drop what other operators left in this worker and give freed memory back to the system.

    Workers outlive stages, so without this a stage would pay for the caches of all before it.
    """
    for cached in _KEPT:
        if cached not in keep:
            cached.cache_clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the C library, where it has one
    if trim:
        trim(0)


def by_bytes(batches: Iterator[pa.RecordBatch], column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The rows of Arrow batches, in slices of about ``limit`` bytes of ``column`` each.

    A row longer than the limit is a slice of its own, so memory follows the
    longest text and not the number of rows in a batch.
    """
    for batch in batches:
        sizes = pc.binary_length(batch.column(batch.schema.get_field_index(column))).fill_null(0).to_pylist()
        start = held = 0
        for i, n in enumerate(sizes):
            if i > start and held + n > limit:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += n
        if start < len(sizes):
            yield batch.slice(start)
