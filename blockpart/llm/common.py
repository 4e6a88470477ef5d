"""What the training-data operators share: scratch tables and byte-level text primitives.

Texts are handled as the UTF-8 bytes of an Arrow column. A null text counts as empty. Words are found with a
table of 256 flags, so a word class must be the same for all bytes of a multi-byte character.
"""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 2 << 20
#: Bytes of an Arrow batch between the JVM and a Python worker, as both sides hold it whole; by rows alone it would grow with the texts' length.
BATCH_BYTES = 8 << 20


# ---- scratch -----------------------------------------------------------------------------------------------------

_OWN: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """A fresh folder name in the shared folder that the session names; a private one only where none is named."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            base = spark.conf.get("spark.sql.warehouse.dir")
        else:
            if "dir" not in _OWN:
                _OWN["dir"] = tempfile.mkdtemp(prefix="blockpart-")
                atexit.register(shutil.rmtree, _OWN["dir"], ignore_errors=True)
            base = f"file://{_OWN['dir']}"
    return f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}"


def materialise(df: DataFrame, codec: str = "zstd") -> DataFrame:
    """Write to the shared folder and read back: cuts the lineage and survives lost executors."""
    path = scratch_dir(df.sparkSession)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Remove the files of a materialised frame that nothing reads any more."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def mapped(df: DataFrame, run, schema) -> DataFrame:
    """mapInArrow in batches of about BATCH_BYTES (a longer row stands alone), unless the session names a size."""
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    if conf.get(key, None) is None:
        conf.set(key, str(BATCH_BYTES))
    return df.mapInArrow(run, schema)


def documents(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hot_share(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


# ---- text as bytes -----------------------------------------------------------------------------------------------

def byte_view(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a text column, end to end, and the n + 1 places where texts begin."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    at = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[at[0] : at[-1]], at - at[0]


def row_slices(at: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about `most` bytes; a longer text stands alone."""
    low, n = 0, len(at) - 1
    while low < n:
        high = max(low + 1, int(np.searchsorted(at, at[low] + most, "right")) - 1)
        yield low, min(high, n)
        low = min(high, n)


def portions(batch: pa.RecordBatch, text: int, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about `most` bytes in its text column."""
    for low, high in row_slices(byte_view(batch.column(text))[1], most):
        yield batch.slice(low, high - low)


def give_back() -> None:
    """Return what a worker process no longer uses to the system; it may serve other tasks for long."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:  # glibc only
        trim(0)


def word_spans(flag: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of flagged bytes that cross no text border; and per text the first word's number (n + 1)."""
    first, last = flag.copy(), flag.copy()
    first[1:] &= ~flag[:-1]
    last[:-1] &= ~flag[1:]
    inner = at[(at > 0) & (at < len(flag))]
    first[inner] = flag[inner]
    last[inner - 1] = flag[inner - 1]
    start = np.flatnonzero(first)
    return start, np.flatnonzero(last) + 1, np.searchsorted(start, at)


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def flags(*ranges: tuple[int, int]) -> np.ndarray:
    table = np.zeros(256, bool)
    for low, high in ranges:
        table[low : high + 1] = True
    return table


#: Letters, digits and every byte of a non-ASCII character, after lower-casing.
ALNUM = flags((0x30, 0x39), (0x41, 0x5A), (0x61, 0x7A), (0x80, 0xFF))
#: Everything but the blank characters of ASCII.
SOLID = ~flags((0x20, 0x20), (0x09, 0x0D))


class WordHash:
    """64-bit hashes of many byte ranges at once: differences of prefix sums of byte times power, shifted back by the inverse power."""

    def __init__(self, base: int = 0x9E3779B97F4A7C15):
        self.base, self.back = base | 1, pow(base | 1, -1, 1 << 64)
        self.up, self.down = np.ones(1, np.uint64), np.ones(1, np.uint64)

    def _grow(self, n: int) -> None:
        if len(self.up) <= n:
            n += n >> 3
            for name, base in (("up", self.base), ("down", self.back)):
                step = np.full(n, base, np.uint64)
                step[0] = 1
                setattr(self, name, np.cumprod(step, dtype=np.uint64))

    def __call__(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        if not len(start):
            return np.zeros(0, np.uint64)
        self._grow(len(data) + 1)
        total = np.zeros(len(data) + 1, np.uint64)
        now = total[1:]
        now[:] = data
        now += np.uint64(1)
        now *= self.up[: len(data)]
        np.cumsum(now, out=now)
        out = (total[end] - total[start]) * self.down[start]
        out ^= out >> np.uint64(29)
        out *= np.uint64(0xBF58476D1CE4E5B9)
        return out ^ (out >> np.uint64(32))


def ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, ... (count[0] of them), start[1], ..."""
    if not len(start) or not (total := int(count.sum())):
        return np.zeros(0, np.int64)
    lead = np.cumsum(count) - count
    return np.repeat(start - lead, count) + np.arange(total)


def distinct_rows(df: DataFrame, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("copies"))
