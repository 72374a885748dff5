"""Word and shingle hashing shared by the text operators (numpy, no state
that grows with the input)."""

from __future__ import annotations

import ctypes
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

U64 = np.uint64
#: Rows of whole texts that go to a Python worker at once, and their bytes (one
#: row may be larger).
BATCH_ROWS, BATCH_BYTES = 1000, 2 << 20


def small_batches(spark) -> None:
    """Lower the session's Arrow batches to ``BATCH_ROWS`` and ``BATCH_BYTES``
    where they are larger: with whole texts the defaults (10,000 rows, 64 MB)
    take too much of an executor."""
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{key}"
        held = spark.conf.get(key, None)
        if held is None or not 0 < int(re.sub(r"\D", "", held) or 0) <= most or not held.isdigit():
            spark.conf.set(key, most)


def bounded(batch: pa.RecordBatch, column: int, most: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose values in a column of strings or bytes take at
    most ``most`` bytes together, or that have one row."""
    if batch.num_rows == 0:
        return
    ends = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64).cumsum()
    at = 0
    while at < batch.num_rows:
        before = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + most, side="right")))
        yield batch.slice(at, to - at)
        at = to


def _hand_back() -> None:
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not the GNU C library: it keeps what it has
        pass


def tidy(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` for ``mapInArrow``; a worker that has finished a partition stays
    alive for the next one, so it gives its free memory back to the system."""
    def whole(batches: Iterator) -> Iterator:
        yield from run(batches)
        _hand_back()
    return whole


_MULTIPLIER = U64(0x9E3779B97F4A7C15)


class WordHashes(dict):
    """bytes -> 64-bit hash; keeps at most ``limit`` words between documents."""

    def __init__(self, limit: int = 50_000):
        super().__init__()
        self.limit = limit

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(word)
        if len(self) < self.limit:
            self[word] = h
        return h


def finish(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit mixing, so that low and high bits both spread."""
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def shingle_set(text: bytes | None, n: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct hashes of the n-word shingles of a whole text.

    Words are maximal runs without ASCII white space, A-Z lower-cased.  A text
    of 1 to n-1 words has one shingle, its whole sequence; a null text or one
    without words has none.
    """
    words = text.lower().split() if text else ()
    k = len(words)
    if not k:
        return np.empty(0, U64)
    w = np.fromiter(map(hashes.__getitem__, words), U64, k)
    span = min(k, n)
    acc = w[:k - span + 1].copy()
    for j in range(1, span):
        acc = acc * _MULTIPLIER + w[j:k - span + 1 + j]
    return np.unique(finish(acc + U64(span)))
