"""Shared pieces: working folders, guarded broadcasts, and vectorised words and hashes.

Words are hashed to 64 bits.  Among v different words about v*v / 2**65 pairs share a hash:
one in ten million at ten million words.
"""

from __future__ import annotations

import ctypes
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import IntegralType

#: White space of the word rule: 0x20 and 0x09 to 0x0D.
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 9, 10, 11, 12, 13]] = True
#: Byte after lower-casing A-Z.
_LOW = np.arange(256, dtype=np.uint8)
_LOW[65:91] += 32
#: What a byte adds to a word's hash: 0 for white space.
_LOW_VALUE = np.where(_BLANK, 0, _LOW.astype(np.uint64) + 1).astype(np.uint64)
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that driver and executors share: spark.checkpoint.dir.

    Where it is unset, a temporary folder serves if the session runs on this machine alone (tests); on a cluster that is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="twigmine-")
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def store(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives lost executors."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(spark: SparkSession, *stored: DataFrame) -> None:
    """Delete stored tables that no later plan reads, and let Spark drop shuffles that nothing refers to."""
    jvm = spark.sparkContext._jvm
    hadoop = spark.sparkContext._jsc.hadoopConfiguration()
    for df in stored:
        for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(hadoop).delete(path, True)
    jvm.System.gc()


def whole_numbers(df: DataFrame, column: str) -> None:
    """TypeError unless a column holds whole numbers: operators that order and link rows by their ids keep them as BIGINT."""
    kind = df.schema[column].dataType
    if not isinstance(kind, IntegralType):
        raise TypeError(f"{column} is {kind.simpleString()}; whole numbers are asked for")


def width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def trim() -> None:
    """Give freed memory of this Python worker back to the system: workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over 64 bits."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def powers(n: int) -> np.ndarray:
    out = np.full(max(n, 1), _BASE, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All UTF-8 bytes of a string column and the offsets of its texts; null is empty."""
    column = (column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column).cast(pa.large_string()).fill_null("")
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words, and for each text the index of its first word (one entry more than texts)."""
    word = ~_BLANK[data]
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1]
    last[:-1] &= ~word[1:]
    cuts = offsets[(offsets > 0) & (offsets < len(data))]
    first[cuts] |= word[cuts]
    last[cuts - 1] |= word[cuts - 1]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each word, A-Z lower-cased."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lengths = np.diff(np.append(starts, len(data)))
    tail = data[starts[0] :]
    at = np.arange(len(tail)) - np.repeat(starts - starts[0], lengths)
    # A word touching the next text's word has no blank between them: the span ends where the next starts.
    values = _LOW_VALUE[tail] * powers(int(lengths.max()))[at]
    return mix(np.add.reduceat(values, starts - starts[0]) + (ends - starts).astype(np.uint64))


def hashed_words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of a column and where each text's words begin."""
    data, offsets = text_bytes(column)
    starts, ends, first = word_spans(data, offsets)
    return word_hashes(data, starts, ends), first


def pieces(batch: pa.RecordBatch, column: str, limit: int = 2_000_000):
    """Slices of a batch of at most about limit bytes of text each (a longer text stands alone)."""
    if not batch.num_rows:
        return
    sizes = np.diff(text_bytes(batch.column(column))[1])
    at = 0
    total = np.cumsum(sizes)
    while at < len(sizes):
        done = total[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(total, done + limit, side="right")))
        yield batch.slice(at, to - at)
        at = to
