"""Shared pieces of the training-data operators: byte-level word tables, stable hashes, Arrow plumbing.

All hashes here are stable across processes and machines: they depend on the bytes only.
"""

from __future__ import annotations

import ctypes
import posixpath
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that one numpy step looks at; longer texts form a step of their own.
SLICE_BYTES = 1 << 18
#: Rows of one transfer between the JVM and Python: with texts of some kilobytes, a few megabytes.
BATCH_ROWS = 1_000

_ODD = np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x5851F42D4C957F2D
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}

#: The six separators space, \t, \n, \v, \f, \r; every other byte belongs to a word.
PLAIN_WORD = np.ones(256, bool)
PLAIN_WORD[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
#: Letters and digits of ASCII and every byte of a longer UTF-8 sequence.
ALNUM_WORD = np.zeros(256, bool)
ALNUM_WORD[0x80:] = True
for _span in (b"09", b"AZ", b"az"):
    ALNUM_WORD[_span[0] : _span[1] + 1] = True
#: A-Z to a-z, other bytes as they are.
LOWER_ASCII = np.arange(256, dtype=np.uint8)
LOWER_ASCII[0x41:0x5B] += 32


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit integers."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _power_table(base: int, size: int) -> np.ndarray:
    """base**0 .. base**(size-1) modulo 2**64, kept and doubled as needed."""
    table = _powers.get(base)
    if table is None or len(table) < size:
        steps = np.full(max(size, 1 << 16), base, np.uint64)
        steps[0] = 1
        table = _powers[base] = np.cumprod(steps, dtype=np.uint64)
    return table[:size]


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each values[start:end], from one prefix sum of a polynomial modulo 2**64."""
    n = len(values)
    prefix = np.zeros(n + 1, np.uint64)
    np.cumsum((values.astype(np.uint64) + np.uint64(1)) * _power_table(_BASE, n), out=prefix[1:])
    raw = (prefix[ends] - prefix[starts]) * _power_table(_BASE_INVERSE, n + 1)[starts]
    return mix64(raw + (ends - starts).astype(np.uint64) * _ODD)


@dataclass
class Words:
    """The words of some texts: byte spans, the text each belongs to, and where each text's words begin."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray  # text i has the words first[i] .. first[i + 1] - 1
    hashes: np.ndarray

    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and its n + 1 offsets; nulls count as empty."""
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    if not len(offsets):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if offsets[-1] > offsets[0] else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def words_of(column: pa.Array, word_bytes: np.ndarray = PLAIN_WORD, fold: np.ndarray | None = None) -> Words:
    data, offsets = text_bytes(column)
    if fold is not None:
        data = fold[data]
    inside = np.zeros(len(data) + 1, bool)
    inside[:-1] = word_bytes[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    stops = inside.copy()
    stops[:-1] &= ~inside[1:]
    cut = offsets[1:-1]  # a text may end in the middle of what looks like one word with the next
    begins[cut] = inside[cut]
    last = cut[cut > 0] - 1
    stops[last] = inside[last]
    starts, ends = np.flatnonzero(begins[:-1]), np.flatnonzero(stops[:-1]) + 1
    return Words(data, starts, ends, np.searchsorted(starts, offsets), span_hashes(data, starts, ends))


def run_hashes(values: np.ndarray, width: int) -> np.ndarray:
    """Hash of every run of `width` consecutive 64-bit values."""
    n = len(values) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    at = np.arange(n)
    return span_hashes(values, at, at + width)


def byte_slices(batch: pa.RecordBatch, text: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in pieces of at most about `limit` text bytes, one row at least."""
    column = batch.column(batch.schema.get_field_index(text))
    _, offsets = text_bytes(column)
    at = 0
    while at < batch.num_rows:
        stop = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield batch.slice(at, stop - at)
        at = stop


def map_texts(df: DataFrame, step: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str, text: str = "text", limit: int = SLICE_BYTES) -> DataFrame:
    """step over bounded pieces of df in Arrow form. Nothing outlives a piece, so a task's memory doesn't grow with its rows."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                for piece in byte_slices(batch, text, limit):
                    yield step(piece)
        give_back()

    small_batches(df.sparkSession)
    return df.mapInArrow(pieces, schema)


def small_batches(spark: SparkSession) -> None:
    """Let the session send texts to Python in batches of at most BATCH_ROWS rows. A lower setting stays."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name, "10000")) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def give_back() -> None:
    """Return memory that this worker holds but doesn't use, as workers are reused from task to task."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its own counsel
        pass


def column_of(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def records(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns.values()], names=list(columns))


def list_array(values, lengths: np.ndarray) -> pa.Array:
    """A list column from flat values and the number that each row owns."""
    offsets = np.zeros(len(lengths) + 1, np.int32)
    np.cumsum(lengths, out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets), values if isinstance(values, pa.Array) else pa.array(values))


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only where it is unset, as in tests, a folder under the warehouse."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = posixpath.join(spark.conf.get("spark.sql.warehouse.dir"), "shared")
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a table in the shared folder: cuts the lineage, and lost executors don't lose it."""
    spark = df.sparkSession
    path = posixpath.join(shared_folder(spark), f"{name}-{uuid.uuid4().hex}")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def uniform(key, salt: int):
    """A number in [0, 1) that follows from the key alone."""
    return F.pmod(F.xxhash64(key, F.lit(salt)), F.lit(1 << 40)) / F.lit(float(1 << 40))


def crc_bucket(key, buckets: int):
    """crc32 of the key's text modulo buckets; a null key counts as empty text."""
    return F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")) % F.lit(buckets)
