"""Helpers that all operators of this subpackage share."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a kernel looks at together; a longer text is looked at alone.
SLICE_BYTES = 1 << 18
#: Bytes of a batch of rows between the JVM and Python.
BATCH_BYTES = 1 << 21
#: Rows of (long, long) that may be broadcast: 32 MB.
BROADCAST_ROWS = 1 << 20

_local: list[str] = []
_tables: list[str] = []


def scratch_root(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one if a local master has none."""
    shared = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return shared
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="quillon-"))
        atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
    return _local[0]


def stored(df: DataFrame, what: str) -> DataFrame:
    """`df` written as Parquet to the shared folder and read again, which cuts its lineage there; see `discard`."""
    path = f"{scratch_root(df.sparkSession)}/quillon-{what}-{uuid.uuid4().hex}"
    bounded_batches(df.sparkSession)
    df.write.parquet(path)
    _tables.append(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._quillon_path = path
    return out


def discard(spark: SparkSession, *tables: DataFrame | None) -> None:
    """Deletes stored tables that nothing reads any more; without `tables`, all that this process stored."""
    for path in [t._quillon_path for t in tables if t is not None] if tables else list(_tables):
        if path in _tables:
            _tables.remove(path)
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def bounded_batches(spark: SparkSession) -> None:
    """Bounds the bytes of a batch for Python, a setting of the running session, unless it is smaller already."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(name, None)
    if now is None or not now.isdigit() or int(now) > BATCH_BYTES:
        spark.conf.set(name, str(BATCH_BYTES))


def release() -> None:
    """Gives memory that is free in this process back to the system."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def map_batches(df: DataFrame, run: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """mapInArrow with batches of bounded size, which leaves no free memory behind in the worker."""
    bounded_batches(df.sparkSession)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return df.mapInArrow(each, schema)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """`df` with a broadcast hint if a count shows that it has `rows` rows at most; else as it is."""
    return F.broadcast(df) if df.count() <= rows else df


def crc_held_out(doc_id: str = "doc_id"):
    """Column: crc32 of the id as text leaves remainder 0 by 5."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the n + 1 offsets of its texts in them (null: empty)."""
    column = column.fill_null("") if column.null_count else column
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None or not len(column):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    return np.frombuffer(data, np.uint8)[at[0] : at[-1]], at - at[0]


def slices(offsets: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose bytes together stay within `most`, or that are one row."""
    start, n = 0, len(offsets) - 1
    while start < n:
        end = max(start + 1, int(np.searchsorted(offsets, offsets[start] + most, side="right")) - 1)
        yield start, end
        start = end


def text_slices(batches: Iterable[pa.RecordBatch], column: str = "text") -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Batches cut so that their texts stay within SLICE_BYTES: (rows, bytes, offsets)."""
    for batch in batches:
        data, at = utf8(batch.column(batch.schema.get_field_index(column)))
        for a, b in slices(at):
            yield batch.slice(a, b - a), data[at[a] : at[b]], at[a : b + 1] - at[a]


def row_slices(batches: Iterable[pa.RecordBatch], column: str = "text") -> Iterator[pa.RecordBatch]:
    for rows, _, _ in text_slices(batches, column):
        yield rows
