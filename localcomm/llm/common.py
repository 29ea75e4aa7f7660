"""Shared pieces: folders every executor sees, Arrow buffers as numpy arrays, byte hashing."""

from __future__ import annotations

import contextlib
import ctypes
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed odd multiplier and the two mixing constants of the public splitmix64 finaliser.
MULT = np.uint64(0x9E3779B97F4A7C15)
MIX_A = np.uint64(0xBF58476D1CE4E5B9)
MIX_B = np.uint64(0x94D049BB133111EB)

#: Powers of MULT for places 0..255 of a run of bytes; longer runs reuse them with a salt per lap.
with np.errstate(over="ignore"):
    POWERS = np.cumprod(np.full(256, MULT, dtype=np.uint64))


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir, or in one process a folder of our own (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        known = spark.sparkContext.getCheckpointDir()
        if known:
            return known
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="localcomm-shared-")
        spark.sparkContext.setCheckpointDir(f"file://{root}")
        root = spark.sparkContext.getCheckpointDir()
    return root


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write a table to the shared folder and read it again: lineage ends here and a lost executor costs no rerun."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    writer = df.write.mode("overwrite").option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_path = path
    return out


def dropped(spark: SparkSession, path: str) -> None:
    """Delete a staged folder through Hadoop's file system, wherever it lives."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Scratch:
    """Tables staged on the way to one result, dropped when it has been written."""

    def __init__(self, spark: SparkSession):
        self.spark, self.held = spark, {}

    def staged(self, df: DataFrame, name: str) -> DataFrame:
        out = staged(df, name)
        self.held[out.staged_path] = True
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Tables that nothing reads any more."""
        for t in tables:
            if self.held.pop(t.staged_path, False):
                dropped(self.spark, t.staged_path)

    def last(self, df: DataFrame, name: str, keep: list[DataFrame] = ()) -> DataFrame:
        """Write the result and drop all that led to it, but for tables that are results too."""
        out = staged(df, name)
        for path in [x for x in self.held if x not in {k.staged_path for k in keep}]:
            del self.held[path]
            dropped(self.spark, path)
        return out


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, with underscores in front where the table has a column of that name already."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name in taken:
            name = f"_{name}"
        out.append(name)
    return out


def tidy(job):
    """The job of a mapInArrow, after which its worker gives freed memory back to the system: it serves tasks of many stages."""

    def run(batches):
        try:
            yield from job(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # not every C library has it
                ctypes.CDLL(None).malloc_trim(0)

    return run


def flat(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A string or binary Arrow array as (bytes, offsets) without copying; nulls count as empty."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    if arr.null_count:
        arr = arr.fill_null(b"" if pa.types.is_binary(arr.type) or pa.types.is_large_binary(arr.type) else "")
    wide = pa.types.is_large_binary(arr.type) or pa.types.is_large_string(arr.type)
    if not len(arr):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(arr.buffers()[1], dtype=np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    data = arr.buffers()[2]
    buf = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return buf[offs[0] : offs[-1]], offs - offs[0]


def slices(offs: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Ranges of rows of at most `most` bytes together, or one longer row."""
    i, n = 0, len(offs) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + most, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def mixed(h: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit hashes."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(30))) * MIX_A
        h = (h ^ (h >> np.uint64(27))) * MIX_B
    return h ^ (h >> np.uint64(31))


def run_hashes(values: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each run values[start : start+length]; the runs tile `values` in order."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    place = np.arange(len(values), dtype=np.int64) - np.repeat(starts, lengths)
    with np.errstate(over="ignore"):
        v = (values.astype(np.uint64) + np.uint64(1)) * POWERS[place & 255]
        if int(lengths.max()) > 256:
            v = v ^ mixed((place >> 8).astype(np.uint64)) * (place > 255)
        sums = np.add.reduceat(v, starts)
        return mixed(sums + lengths.astype(np.uint64) * MIX_B)


def texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", binary: bool = False) -> DataFrame:
    """(id, text) with null texts empty; as bytes when asked."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return df.select(F.col(id_col).cast("long").alias(id_col), (text.cast("binary") if binary else text).alias(text_col))
