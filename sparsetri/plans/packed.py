"""Rows of whole numbers that cross the network in sorted packs.

A shuffled row of two ids takes some dozen bytes of disk even when it is compressed.  A task that sorts what it sends to one place, and keeps differences of
the first column and no more bytes than the other ones need, sends three or four.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PACKS = "b int, size long, packed binary"
#: Rows that a task packs together.
TOGETHER = 2_000_000
Opened = Callable[[int, list[np.ndarray]], Iterator[pa.RecordBatch]]


def _planes(x: np.ndarray) -> bytes:
    """Unsigned numbers: how many bytes the largest takes, then their bytes by place."""
    width = max(1, (int(x.max()).bit_length() + 7) // 8)
    return bytes([width]) + x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def pack(columns: list[np.ndarray]) -> bytes:
    """Equally long columns, the first in order; differences wrap around, so any ids will do."""
    first, *rest = (c.astype("<i8").view("<u8") for c in columns)
    parts = [first[:1].tobytes(), _planes(np.r_[first[:1] - first[:1], first[1:] - first[:-1]])]
    for c in rest:
        low = c.view("<i8").min(keepdims=True).view("<u8")
        parts += [low.tobytes(), _planes(c - low)]
    raw = b"".join(parts)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unpack(packed: bytes, size: int) -> list[np.ndarray]:
    raw = pa.decompress(packed[8:], int.from_bytes(packed[:8], "little"), codec="zstd", asbytes=True)
    columns, at = [], 0
    while at < len(raw):
        low, width = np.frombuffer(raw, "<u8", 1, at), raw[at + 8]
        x = np.zeros((size, 8), np.uint8)
        x[:, :width] = np.frombuffer(raw, np.uint8, size * width, at + 9).reshape(width, size).T
        x = x.view("<u8")[:, 0]
        columns.append(((x if columns else np.cumsum(x, dtype=np.uint64)) + low).view(np.int64))
        at += 9 + size * width
    return columns


def packs(b: np.ndarray, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """A pack for each place b that rows go to."""
    order = np.lexsort((*columns[::-1], b))
    b, columns = b[order], [c[order] for c in columns]
    first = np.flatnonzero(np.r_[True, b[1:] != b[:-1]]) if len(b) else np.empty(0, np.int64)
    ends = np.r_[first[1:], len(b)]
    for k in range(0, len(first), 64):
        cuts = list(zip(first[k : k + 64].tolist(), ends[k : k + 64].tolist(), strict=True))
        held = [pack([c[low:high] for c in columns]) for low, high in cuts]
        yield pa.RecordBatch.from_arrays([pa.array(b[first[k : k + 64]], pa.int32()), pa.array([high - low for low, high in cuts], pa.int64()), pa.array(held, pa.binary())], names=["b", "size", "packed"])


def gathered(batches: Iterator[pa.RecordBatch], rows: int = TOGETHER) -> Iterator[list[np.ndarray]]:
    """Columns of about so many rows, whatever the size of a batch."""
    parts, size = [], 0
    for batch in batches:
        parts.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
        size += batch.num_rows
        if size >= rows:
            yield [np.concatenate(c) for c in zip(*parts, strict=True)]
            parts, size = [], 0
    if size:
        yield [np.concatenate(c) for c in zip(*parts, strict=True)]


def _packing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b, *columns in gathered(batches):
        yield from packs(b, columns)


def opened(packed: DataFrame, n: int, then: Opened, schema: str) -> DataFrame:
    """PACKS for n places -> what then(b, columns) makes of all rows of each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[list[np.ndarray]]] = {}
        for batch in batches:
            for b, size, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                held.setdefault(b, []).append(unpack(x.as_py(), size))
        for b in sorted(held):
            yield from then(b, [np.concatenate(c) for c in zip(*held.pop(b), strict=True)])

    return packed.repartitionById(n, F.col("b")).mapInArrow(run, schema)


def moved(rows: DataFrame, n: int, then: Opened, schema: str) -> DataFrame:
    """Rows (b, whole numbers without nulls), each moved to its place b of n."""
    return opened(rows.mapInArrow(_packing, PACKS), n, then, schema)


def place(x: np.ndarray, n: int) -> np.ndarray:
    """One of n places for each id."""
    return (((x.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)) % np.uint64(n)).astype(np.int32)
