"""Arrow text columns as numpy arrays, in pieces of bounded size."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from wordlid.io import bound_batches

#: Bytes that are looked at together; one longer text is a piece of its own.
PIECE = 1 << 20

_space = np.zeros(256, bool)
_space[[9, 10, 11, 12, 13, 32]] = True
_lower = np.arange(256, dtype=np.uint64)
_lower[65:91] += 32

ODD = np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """Spread 64-bit values, one to one."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def tidied(run: Callable) -> Callable:
    """run, a function from batches to batches, and then what it has freed back to the system: workers live on for other stages."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # not every C library has it
                ctypes.CDLL(None).malloc_trim(0)

    return whole


def mapped(df: DataFrame, run: Callable, schema) -> DataFrame:
    """df through run, in batches of bounded size."""
    bound_batches(df.sparkSession)
    return df.mapInArrow(tidied(run), schema)


def powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; a null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, "")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, ends, data = column.buffers()
    offsets = np.frombuffer(ends, np.int64)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8), offsets


def pieces(offsets: np.ndarray, most: int = PIECE) -> Iterator[tuple[int, int]]:
    """Runs [i, j) of texts of about `most` bytes."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of the texts that offsets bound in data: a hash of each lower-cased word, and the text it is in."""
    low, high = int(offsets[0]), int(offsets[-1])
    part, ends = data[low:high], offsets - low
    if not len(part):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    black = ~_space[part]
    first = black.copy()
    first[1:] &= ~black[:-1]
    heads = ends[:-1][ends[:-1] < ends[1:]]
    first[heads] = black[heads]
    starts = np.flatnonzero(first)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    size = np.diff(np.append(starts, len(part)))
    at = np.arange(int(starts[0]), len(part)) - np.repeat(starts, size)
    value = (_lower[part[starts[0] :]] + np.uint64(1)) * black[starts[0] :]
    value *= powers(ODD, int(size.max()))[at]
    return mixed(np.add.reduceat(value, starts - starts[0])), np.searchsorted(ends, starts, side="right") - 1


def shingles(data: np.ndarray, offsets: np.ndarray, size: int = 5) -> list[np.ndarray]:
    """For each text the sorted set of its word n-grams; with fewer words the whole sequence as one, without words none."""
    n = len(offsets) - 1
    word, text = words(data, offsets)
    counts = np.bincount(text, minlength=n) if len(text) else np.zeros(n, np.int64)
    begin = np.concatenate([[0], np.cumsum(counts)])
    run = np.zeros(max(0, len(word) - size + 1), np.uint64)
    for k in range(size):
        run = run * ODD + word[k : k + len(run)]
    run = mixed(run)
    out = []
    for i in range(n):
        b, c = begin[i], counts[i]
        if c >= size:
            out.append(np.unique(run[b : b + c - size + 1]))
        elif c:
            whole = np.uint64(c)
            for w in word[b : b + c]:
                whole = np.uint64((int(whole) * int(ODD) + int(w)) % 2**64)
            out.append(mixed(np.array([whole ^ np.uint64(0xA5A5A5A5)], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out
