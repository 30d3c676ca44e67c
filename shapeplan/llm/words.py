"""Words, stable word hashes and Arrow helpers used by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import functools
import gc
import inspect
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  used as pa.compute
import xxhash

#: A word, as every contract of this subpackage has it: a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

_M1 = np.uint64(0xBF58476D1CE4E5B9)
_M2 = np.uint64(0x94D049BB133111EB)
_GOLD = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit integers (the finaliser of splitmix64)."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x = x ^ (x >> np.uint64(27))
    x = x * _M2
    return x ^ (x >> np.uint64(31))


class WordHashes(dict):
    """Word to 64-bit hash. Emptied when full, so that memory stays bounded."""

    def __init__(self, most: int = 200_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


#: The hashes of a worker's words, shared by all operators; emptied after each task.
hashes = WordHashes()


def release() -> None:
    """Give memory back: workers are reused, and what one operator leaves would add to the next one's."""
    hashes.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # a C library without it
        pass


def tidy(work: Callable) -> Callable:
    """Release memory when a worker's task, a generator of batches, is over."""
    assert inspect.isgeneratorfunction(work)

    @functools.wraps(work)
    def run(*args, **how):
        try:
            yield from work(*args, **how)
        finally:
            release()

    return run


def grouped(work: Callable, **how) -> Callable:
    """``work`` with further arguments as a function of a group's batches; memory is released after each group."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from work(batches, **how)
        finally:
            release()

    return run


def paired(work: Callable, form: pa.Schema, **how) -> Callable:
    """``work``, a generator of batches, with further arguments as a function of two groups of one key."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        try:
            return pa.Table.from_batches(work(left, right, **how), form)
        finally:
            release()

    return run


def split(text: bytes | None, lower: bool = False) -> list[bytes]:
    """The words of a text; null counts as empty. ``bytes`` methods touch ASCII only, as wanted."""
    if not text:
        return []
    return (text.lower() if lower else text).split()


def ngram_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of ``n`` words, in place order; one hash of all when there are fewer."""
    if not len(h):
        return h
    n = min(n, len(h))
    out = np.full(len(h) - n + 1, n, np.uint64)
    with np.errstate(over="ignore"):
        for i in range(n):
            out = mix(out * _GOLD + h[i : len(h) - n + 1 + i])
    return out


def column(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def texts(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    return batch.column(batch.schema.get_field_index(name)).cast(pa.large_binary()).to_pylist()


def slices(batches: Iterator[pa.RecordBatch], name: str, most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Batches re-cut so that each holds about ``most`` bytes of the column ``name`` (one row at least)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        lengths = pa.compute.fill_null(pa.compute.binary_length(batch.column(batch.schema.get_field_index(name))), 0)
        ends = np.cumsum(lengths.to_numpy(zero_copy_only=False).astype(np.int64) + 64)
        start = 0
        while start < batch.num_rows:
            floor = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, floor + most, "right")))
            yield batch.slice(start, stop - start)
            start = stop


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
