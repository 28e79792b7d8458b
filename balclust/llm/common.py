"""What the operators of this package share: reading, staging, Arrow slices, hashing of byte runs."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one step of a Python worker holds at a time (a longer single text is one step).
SLICE_BYTES = 2 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share. Only a local master gets one of our own; on a cluster that names none this raises ValueError."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        if not context.master.startswith("local"):
            raise ValueError("name a folder that driver and executors share in spark.checkpoint.dir")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="balclust-"))
    return context.getCheckpointDir().rstrip("/")


def stage(df: DataFrame) -> DataFrame:
    """Write df once to the shared folder and read it back: later steps neither recompute it nor lose it with an executor."""
    spark, path = df.sparkSession, f"{shared_dir(df.sparkSession)}/staged/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop(spark: SparkSession, *staged: DataFrame) -> None:
    """Delete the tables behind frames that stage gave, once nothing reads them any more."""
    for frame in staged:
        for file in frame.inputFiles()[:1]:
            path = spark._jvm.org.apache.hadoop.fs.Path(file).getParent()
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def drop_stages(spark: SparkSession) -> None:
    """Delete the tables that steps have written; frames that read them are of no use afterwards."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/staged")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Let the cleaner drop shuffle files of steps that are over: it acts once the driver's JVM has collected its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts on end, and where each begins (one more: the end). Nulls are empty."""
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    where = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = column.buffers()[2]
    if data is None or where[-1] == where[0]:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    return np.frombuffer(data, np.uint8)[where[0] : where[-1]], where - where[0]


def slices(batches: Iterator[pa.RecordBatch], column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in runs of rows whose texts hold at most so many bytes together, or of one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        where = text_bytes(batch.column(batch.schema.get_field_index(column)))[1]
        start = 0
        while start < batch.num_rows:
            stop = max(start + 1, int(np.searchsorted(where, where[start] + most, "right")) - 1)
            yield batch.slice(start, stop - start)
            start = stop
        del batch, where
    give_back()


def give_back() -> None:
    """Return freed memory to the system: a worker that waits for its next task should hold little."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def as_row(df: DataFrame) -> DataFrame:
    """Each row as one struct named row: no column of df can meet one of ours."""
    return df.select(F.struct(*(F.col("`" + c.replace("`", "``") + "`") for c in df.columns)).alias("row"))


def from_row(df: DataFrame, columns: list[str], **own: Column) -> DataFrame:
    """The way back; own: columns that take the place of those of the row, where it has them."""
    return df.select(*(own[c].alias(c) if c in own else F.col("row").getField(c).alias(c) for c in columns))


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def raw_texts(batch: pa.RecordBatch, name: str = "text") -> list[bytes]:
    """Each text's UTF-8 bytes; null is empty."""
    return pc.fill_null(column(batch, name), "").cast(pa.binary()).to_pylist()


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    have = _POWERS.get(base)
    if have is None or len(have) < n:
        size = 1 << max(16, (n - 1).bit_length())
        have = np.full(size, base, np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if size <= 1 << 23:
            _POWERS[base] = have
    return have[:n]


#: One random word for each byte value.
BYTE_WORDS = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))


class RunHash:
    """Rolling hash: the 64-bit hash of any run of a sequence of words in constant time, from one prefix sum."""

    def __init__(self, words: np.ndarray):
        self.sums = np.zeros(len(words) + 1, np.uint64)
        np.cumsum(words * _powers(_BASE, len(words)), out=self.sums[1:])
        self.back = _powers(_INVERSE, len(words) + 1)

    def __call__(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        value = (self.sums[stop] - self.sums[start]) * self.back[start]
        return mix(value ^ ((stop - start).astype(np.uint64) * np.uint64(0xA0761D6478BD642F)))


SEPARATORS = np.zeros(256, bool)
SEPARATORS[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def word_runs(data: np.ndarray, where: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs without separators; a run ends with its text."""
    inside = ~SEPARATORS[data]
    edges = where[(where > 0) & (where < len(data))]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    first[edges] = inside[edges]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[edges - 1] = inside[edges - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def repeats(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each key, whether it occurs twice or more, and whether it occurs earlier."""
    n = len(keys)
    if not n:
        return np.zeros(0, bool), np.zeros(0, bool)
    order = np.argsort(keys)
    ranked = keys[order]
    new = np.ones(n, bool)
    new[1:] = ranked[1:] != ranked[:-1]
    heads = np.flatnonzero(new)
    again = np.ones(n, bool)
    again[np.minimum.reduceat(order, heads)] = False
    size = np.diff(np.append(heads, n))
    twice = np.zeros(n, bool)
    twice[order] = np.repeat(size > 1, size)
    return twice, again


def per_row(flags: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sums of flags between consecutive bounds."""
    sums = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=sums[1:])
    return np.diff(sums[bounds])
