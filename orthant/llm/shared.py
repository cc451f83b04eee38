"""Shared-folder tables, Arrow batch slicing and small column helpers for the corpus operators."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that one numpy pass handles at a time; a longer single text is handled alone.
SLICE_BYTES = 1 << 20
#: Rows of an Arrow batch while a working table is written; whole texts make default batches large.
BATCH_ROWS, BATCH_SETTING = 2000, "spark.sql.execution.arrow.maxRecordsPerBatch"
CLEANUP_SETTING = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or (where that is
    unset, as in local tests) a fresh temporary folder that is kept for the session."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        path = getattr(spark.sparkContext, "_corpus_shared_dir", None)
        if not path:
            path = tempfile.mkdtemp(prefix="corpus-shared-")
            spark.sparkContext._corpus_shared_dir = path
    return path.rstrip("/")


#: Paths of working tables by the scope that was open when they were written.
_scopes: dict[str, list[str]] = {}
_open_scope: list[str] = []


def _path(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


@contextlib.contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    before = int(spark.conf.get(BATCH_SETTING))
    spark.conf.set(BATCH_SETTING, str(min(before, BATCH_ROWS) if before > 0 else BATCH_ROWS))
    try:
        yield
    finally:
        spark.conf.set(BATCH_SETTING, str(before))


@contextlib.contextmanager
def freed_shuffles(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what runs inside go as soon as its result is there, not when the driver next collects its garbage."""
    before = spark.conf.get(CLEANUP_SETTING)
    spark.conf.set(CLEANUP_SETTING, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP_SETTING, before)


def release() -> None:
    """Gives memory that a reused Python worker no longer needs back to the system."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def materialize(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Writes ``df`` as Parquet into the shared folder and reads it again, which cuts the lineage
    and survives lost executors. The folder goes when it is discarded or when the session ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with small_batches(spark), freed_shuffles(spark):
        df.write.options(**options).parquet(path)
    target, fs = _path(spark, path)
    fs.deleteOnExit(target)
    if _open_scope:
        _scopes.setdefault(_open_scope[-1], []).append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._shared_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Deletes written tables that nothing reads any more."""
    for f in frames:
        target, fs = _path(f.sparkSession, f._shared_path)
        fs.delete(target, True)


@contextlib.contextmanager
def scope(spark: SparkSession, name: str) -> Iterator[None]:
    """Working tables written inside belong to ``name``; those it still has from before are deleted first. For
    steps of which each begins when the result of the one before has been written."""
    for path in _scopes.pop(name, []):
        target, fs = _path(spark, path)
        fs.delete(target, True)
    _open_scope.append(name)
    try:
        yield
    finally:
        _open_scope.pop()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_remainder(column: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; null where the id is null."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % F.lit(modulus)


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(UTF-8 bytes, offsets) of a string column; a null is an empty text. Views, no copies."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.string())
        width = np.int32
    else:
        width = np.int64
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, width, count=column.offset + n + 1)[column.offset :].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, off


def slices(off: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes, or of one row that is longer."""
    n, at = len(off) - 1, 0
    while at < n:
        end = int(np.searchsorted(off, off[at] + limit, side="right")) - 1
        end = min(n, max(at + 1, end))
        yield at, end
        at = end


def text_parts(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets from 0) for each slice of a string column."""
    raw, off = text_buffers(column)
    for a, b in slices(off):
        yield a, b, raw[off[a] : off[b]], off[a : b + 1] - off[a]
    release()
