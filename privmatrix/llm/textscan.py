"""Vectorised scanning of Arrow string columns: words, 64-bit word hashes, shingle sets and minwise signatures.

Works on the UTF-8 buffer of a whole record batch, cut into slices of about a MB at document bounds, so memory stays
bounded whatever the batch holds (a single document is always scanned whole).
"""

from __future__ import annotations

import ctypes
import re
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

SLICE_BYTES = 1_000_000
ARROW_BYTES = 4 << 20
_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_BYTES = np.random.default_rng(20240117).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_BYTES[65:91] = _BYTES[97:123]  # A-Z hash as a-z
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the base and of its inverse, modulo 2**64."""
    if len(_powers[0]) < n:
        for i, base in enumerate((_BASE, _BASE_INVERSE)):
            grown = np.full(max(n, SLICE_BYTES + 1), base, np.uint64)
            grown[0] = 1
            _powers[i] = np.multiply.accumulate(grown)
    return _powers[0][:n], _powers[1][:n]


def free_powers() -> None:
    """Forget the tables of powers, which are needed only while texts are scanned."""
    _powers[:] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets (one more than rows) of a string column; a null has no bytes."""
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, last row, bytes, offsets) of slices of about SLICE_BYTES, never cutting a row."""
    row, rows = 0, len(offsets) - 1
    while row < rows:
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + SLICE_BYTES, "right")) - 1)
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


class Words:
    """Words of a slice: byte starts and ends, hashes, and for each row the index of its first word."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, space: np.ndarray = SPACE):
        n = len(data)
        word = ~space[data]
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        before = np.concatenate(([False], word[:-1])) if n else word
        after = np.concatenate((word[1:], [False])) if n else word
        self.starts = np.flatnonzero(word & (~before | edge[:n]))
        self.ends = np.flatnonzero(word & (~after | edge[1:])) + 1
        self.first = np.searchsorted(self.starts, offsets)
        power, self._inverse = powers(n + 1)
        self._sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_BYTES[data] * power[:n], dtype=np.uint64)))

    def hashes(self) -> np.ndarray:
        return self.span_hashes(self.starts, self.ends)

    def span_hashes(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hash of the bytes of each span, the same wherever the span stands."""
        return mix((self._sums[ends] - self._sums[starts]) * self._inverse[starts] + (ends - starts).astype(np.uint64))


def _weights(k: int) -> np.ndarray:
    return np.random.default_rng(77).integers(1, 1 << 63, 64, dtype=np.uint64)[:k] * np.uint64(2) + np.uint64(1)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int) -> Iterator[np.ndarray]:
    """For each row, the sorted distinct 64-bit hashes of its k-word shingles; the whole sequence if it has fewer words."""
    words = Words(data, offsets)
    h, c = words.hashes(), _weights(k)
    whole = np.zeros(max(0, len(h) - k + 1), np.uint64)
    for j in range(k):
        whole += h[j : j + len(whole)] * c[j]
    whole = mix(whole)
    for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist()):
        if b - a >= k:
            yield np.unique(whole[a : b - k + 1])
        elif b > a:
            yield mix((h[a:b] * c[: b - a]).sum(dtype=np.uint64, keepdims=True) + np.uint64(b - a))
        else:
            yield whole[:0]


class Minwise:
    """t minwise tokens of a set: for each of t random bijections of 32-bit values, the least image."""

    def __init__(self, t: int, seed: int = 5):
        draw = np.random.default_rng(seed)
        self.t = t
        self._flip = draw.integers(0, 1 << 32, t, dtype=np.uint32)
        self._times = draw.integers(0, 1 << 31, t, dtype=np.uint32) * np.uint32(2) + np.uint32(1)

    def __call__(self, hashes: np.ndarray) -> np.ndarray:
        """hashes: at least one."""
        high = (hashes >> np.uint64(32)).astype(np.uint32)
        out = np.full(self.t, 0xFFFFFFFF, np.uint32)
        for a in range(0, len(high), 1024):
            np.minimum(out, ((high[a : a + 1024, None] ^ self._flip) * self._times).min(axis=0), out=out)
        return out


def mapped(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | T.StructType) -> DataFrame:
    """``df.mapInArrow(run, schema)`` with bounded batches, giving freed memory back to the system at the end of a task, as Python workers live on between tasks.

    The session's limit on the bytes of a batch is lowered to ``ARROW_BYTES`` if it is above: batches of ten thousand long texts take a
    hundred MB in the JVM and as much in its worker.
    """
    conf = df.sparkSession.conf
    if _bytes(conf.get(_LIMIT)) > ARROW_BYTES:
        conf.set(_LIMIT, str(ARROW_BYTES))

    @wraps(run)
    def tidy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            trim()

    return df.mapInArrow(tidy, schema)


def _bytes(text: str) -> int:
    """A size setting in bytes, such as 64m or 67108864b."""
    number, unit = re.fullmatch(r"(-?[0-9]+)\s*([a-z]*)", text.strip().lower()).groups()
    return int(number) << {"": 0, "b": 0, "k": 10, "m": 20, "g": 30, "t": 40}[unit.removesuffix("b")[:1]]


def trim() -> None:
    """Drop the tables of powers and give freed memory back to the system."""
    free_powers()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library


def string_column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))
