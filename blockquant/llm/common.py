"""Helpers shared by the operators: shared scratch tables and bounded Arrow batches."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession, name: str) -> str:
    """A new folder that every executor sees, under ``spark.checkpoint.dir``. Where that is unset a temp folder will do only if
    the driver is the one executor."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="blockquant-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends at replicated files, not at executors."""
    path = shared_dir(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Remove shared tables that nothing reads any more."""
    for t in tables:
        context = t.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(t.stored_at)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pieces(batches: Iterator[pa.RecordBatch], text_field: int, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of whole rows with about ``limit`` bytes of text each, so that a worker's memory doesn't follow the batch."""
    for batch in batches:
        sizes = batch.column(text_field).nbytes
        rows = max(1, min(batch.num_rows, int(batch.num_rows * limit / max(1, sizes))))
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)
        give_back()


def give_back() -> None:
    """Return freed memory to the system: a worker outlives its task, and so does what its allocators keep."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def texts_of(column: pa.Array) -> list[str]:
    """Python strings; null counts as the empty text."""
    return [t or "" for t in column.to_pylist()]


def bucket_of(id_col: str | Column, parts: int) -> Column:
    """crc32 of the id's decimal text, modulo ``parts``: the split rule of training and held-out rows."""
    return F.crc32(F.col(id_col).cast("string") if isinstance(id_col, str) else id_col.cast("string")) % F.lit(parts)
