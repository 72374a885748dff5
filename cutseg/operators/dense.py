"""Sums over a fixed number of buckets, held as dense numpy blocks.

The result's size is a constant of the caller (``buckets`` x 4 bytes), so it
may be collected and broadcast whatever the size of the input.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

BLOCK = 1 << 16
SCHEMA = "block int, counts binary"


def emit(counts: np.ndarray) -> pa.RecordBatch:
    """One row per block of ``counts`` that is not all zero."""
    blocks = [(b, counts[b * BLOCK:(b + 1) * BLOCK]) for b in range(-(-len(counts) // BLOCK))]
    blocks = [(b, x.astype("<u4").tobytes()) for b, x in blocks if x.any()]
    return pa.RecordBatch.from_arrays(
        [pa.array([b for b, _ in blocks], pa.int32()), pa.array([x for _, x in blocks], pa.binary())], ["block", "counts"])


def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for b, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            x = np.frombuffer(x, "<u4").astype(np.int64)
            total[b] = total[b] + x if b in total else x
    blocks = sorted(total)
    yield pa.RecordBatch.from_arrays(
        [pa.array(blocks, pa.int32()), pa.array([np.minimum(total[b], 2**32 - 1).astype("<u4").tobytes() for b in blocks], pa.binary())],
        ["block", "counts"])


def collect_sums(parts: DataFrame, buckets: int) -> np.ndarray:
    """Add block rows of all partitions; sums saturate at 2**32 - 1."""
    merged = parts.mapInArrow(_add, SCHEMA).repartition(max(1, -(-buckets // BLOCK)), "block").mapInArrow(_add, SCHEMA)
    out = np.zeros(-(-buckets // BLOCK) * BLOCK, np.uint32)
    for row in merged.collect():
        x = np.frombuffer(row["counts"], "<u4")
        out[row["block"] * BLOCK:row["block"] * BLOCK + len(x)] = x
    return out[:buckets]
