"""Shared helpers: the shared work folder, written intermediate tables, Arrow slices of text."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Bytes of text that a vectorised kernel takes at once; its temporary arrays are about 40 times as large.
PIECE = 1 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def work_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below spark.checkpoint.dir, which all executors share; a local one only where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        context = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = context.get() if context.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir is not set: executors need a folder that all of them reach")
        base = tempfile.mkdtemp(prefix="runloom-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/runloom-{name}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, name: str, *used: DataFrame) -> DataFrame:
    """df, cut from its lineage by a Parquet table in the shared folder; a lost executor only repeats its own tasks. used: tables to discard then."""
    spark = df.sparkSession
    path = work_dir(spark, name)
    with shuffles_dropped(spark):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _paths[id(out)] = (out, path)
    discard(*used)
    return out


def tidy() -> None:
    """Gives memory that a kernel has freed back to the system: the worker that ran it stays alive."""
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


def settle(spark: SparkSession) -> None:
    """After a phase of many jobs: the driver gives freed memory back, and Spark's cleaner sees what nothing refers to any more."""
    gc.collect()
    tidy()
    spark._jvm.System.gc()


def _trimmer():
    import ctypes

    try:
        return ctypes.CDLL(None).malloc_trim
    except (OSError, AttributeError):  # not glibc
        return None


_trim = _trimmer()


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Queries that end in here delete their shuffle files at once: phases of an operator do not add up on disk."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


_paths: dict[int, tuple[DataFrame, str]] = {}


def discard(*tables: DataFrame) -> None:
    """Deletes tables of written() that nothing reads any more."""
    for df in tables:
        _, path = _paths.pop(id(df))
        where = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


def texts(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    """A string column as one array without nulls (null: empty)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return pc.fill_null(column, "")


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and the n + 1 offsets of a null-free string array."""
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def pieces(column: pa.Array, limit: int = PIECE) -> Iterator[tuple[int, int]]:
    """Row ranges of at most limit bytes of text, or of one longer text."""
    if not len(column):
        return
    _, offs = buffers(column)
    start = 0
    while start < len(column):
        stop = max(start + 1, int(np.searchsorted(offs, offs[start] + limit, "right")) - 1)
        yield start, min(stop, len(column))
        start = stop


#: Bits of a filter that the driver builds and broadcasts: 4 MB whatever the input; a fuller one only lets more rows pass.
FILTER_BITS = 1 << 25


def bit_filter(keys: DataFrame) -> np.ndarray:
    """Bytes of a filter over one long column: at most FILTER_BITS / 64 rows reach the driver."""
    low = f"`{keys.columns[0]}` & {FILTER_BITS - 1}L"
    rows = keys.selectExpr(f"shiftright({low}, 6) AS w", f"shiftleft(1L, int(({low}) & 63)) AS b")
    found = rows.groupBy("w").agg({"b": "bit_or"}).toDF("w", "b").toArrow()
    out = np.zeros(FILTER_BITS // 64, np.int64)
    out[found.column("w").to_numpy()] = found.column("b").to_numpy()
    return out.view(np.uint8)


def passes(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """True where a 64-bit key may be in the filter."""
    low = keys.view(np.uint64) & np.uint64(FILTER_BITS - 1)
    return (bits[(low >> np.uint64(3)).astype(np.int64)] >> (low & np.uint64(7)).astype(np.uint8)) & 1 > 0

