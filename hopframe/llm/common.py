"""Shared pieces of the training-data operators: table access, shared staging, text kernels."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable, Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.exec.importing import importable

#: bytes that separate words: space, tab, line feed, vertical tab, form feed, carriage return
SEPARATORS = b"\x20\x09\x0a\x0b\x0c\x0d"
#: text handled at once by the numpy kernels
CHUNK_BYTES = 2 << 20

_IS_WORD = np.ones(256, dtype=bool)
_IS_WORD[list(SEPARATORS)] = False
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: masks that keep the first 0 to 8 bytes of a little-endian integer
_LOW_BYTES = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, through Spark's reader only."""
    importable(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder below ``spark.checkpoint.dir``, which driver and executors share.

    Where the setting is empty (tests), a folder below the warehouse is used.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_stage"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder and read again: lineage ends here, executors may go."""
    spark = df.sparkSession
    path = shared_dir(spark)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fold(doc_id: str = "doc_id", of: int = 4):
    """crc32 of the id's decimal text modulo ``of``."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % of


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` for mapInArrow, after which the worker, which Spark keeps for later tasks, hands freed memory back."""

    def call(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (OSError, AttributeError):  # not with this C library
                pass

    return call


# --- text kernels ---------------------------------------------------------------------------


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets of a string column; null counts as empty. No copy of the text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type)
    buffers, n = column.buffers(), len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(buffers[1], np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def row_chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges that hold about ``limit`` bytes each; a longer row is a range of its own."""
    low, n = 0, len(offsets) - 1
    while low < n:
        high = int(np.searchsorted(offsets, offsets[low] + limit, side="right")) - 1
        high = min(n, max(low + 1, high))
        yield low, high
        low = high


def text_chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    data, offsets = string_buffers(column)
    for low, high in row_chunks(offsets, limit):
        yield low, high, data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low]


def lowered(data: np.ndarray) -> np.ndarray:
    """A-Z to a-z, every other byte as it is."""
    return _LOWER[data]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every word, and for each row (plus one) the number of words before it."""
    if not len(data):
        empty = np.zeros(0, np.int64)
        return empty, empty, np.zeros(len(offsets), np.int64)
    inside = _IS_WORD[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    edges = offsets[:-1][offsets[:-1] < len(data)]
    begins[edges] = inside[edges]
    ends = np.empty(len(data), bool)
    ends[-1] = inside[-1]
    ends[:-1] = inside[:-1] & (~inside[1:] | begins[1:])
    starts = np.flatnonzero(begins)
    stops = np.flatnonzero(ends) + 1
    return starts, stops, np.searchsorted(starts, offsets)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def word_codes(data: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """A number for each word, the same for words of equal bytes; it holds for this call only."""
    ends = np.concatenate(([0], np.cumsum(stops - starts)))
    letters = np.ascontiguousarray(data[_IS_WORD[data]])
    words = pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(ends), pa.py_buffer(letters)])
    return words.dictionary_encode().indices.to_numpy()


def word_hashes(data: np.ndarray, starts: np.ndarray, stops: np.ndarray, seed: int = 0) -> np.ndarray:
    """64-bit hash of each word's bytes, the same wherever the word stands; seeds give independent hashes.

    Up to 16 bytes go into two integers, which with the length are mixed by bijections; longer words go through BLAKE2b.
    """
    n = len(starts)
    if not n:
        return np.zeros(0, np.uint64)
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    eight = np.ndarray(len(padded) - 7, np.dtype("<u8"), padded, strides=(1,))  # the 8 bytes from each place on
    sizes = stops - starts
    first, second = (eight[starts + 8 * k] & _LOW_BYTES[np.clip(sizes - 8 * k, 0, 8)] for k in (0, 1))
    key = mixed(np.array([2 * seed + 1, 2 * seed + 2], np.uint64))
    out = mixed(mixed(mixed(first ^ key[0]) + second) ^ key[1] ^ sizes.astype(np.uint64))
    for i in np.flatnonzero(sizes > 16).tolist():
        out[i] = int.from_bytes(_DIGESTS[data[starts[i] : stops[i]].tobytes()][8 * seed : 8 * seed + 8], "little")
    return out


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of every ``width`` consecutive word hashes, by first word; the last ones wrap and are to be masked."""
    n = len(words)
    if n == 0:
        return words
    total = np.zeros(n, np.uint64)
    factor = 1
    for k in range(min(width, n)):
        factor = factor * 0xD1342543DE82EF95 % (1 << 64)
        total[: n - k] += words[k:] * np.uint64(factor)
    return mixed(total)


def binary_column(values: list[bytes]) -> pa.Array:
    return pa.array(values, pa.binary())


class Remembered(dict):
    """Results of ``compute`` by word, in two generations: words in use stay when the older ones go."""

    def __init__(self, compute, generation: int = 180_000, longest: int = 64):
        super().__init__()
        self.compute, self.generation, self.longest, self.old = compute, generation, longest, {}

    def __missing__(self, word):
        value = self.old.get(word)
        if value is None:
            value = self.compute(word)
        if len(word) <= self.longest:
            if len(self) >= self.generation:
                self.old = dict(self)
                self.clear()
            self[word] = value
        return value


#: digests of words of more than 16 bytes, 8 bytes for each seed
_DIGESTS = Remembered(lambda word: blake2b(word).digest(), generation=50_000)
