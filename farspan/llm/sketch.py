"""A count sketch of fixed size over 64-bit keys, filled in tasks and summed by block.

It only ever steers work (which keys count as frequent); its errors never change a result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

BITS = 22
BLOCKS = 64
_BUFFERED = 1 << 21


class Sketch:
    """Counters of one task; keys are gathered and counted in large portions."""

    def __init__(self):
        self.counts = np.zeros(1 << BITS, np.uint32)
        self.held: list[np.ndarray] = []
        self.size = 0

    def add(self, keys: np.ndarray) -> None:
        self.held.append(cell(keys).astype(np.int32))
        self.size += len(keys)
        if self.size >= _BUFFERED:
            self._count()

    def _count(self) -> None:
        if self.held:
            self.counts += np.bincount(np.concatenate(self.held), minlength=len(self.counts)).astype(np.uint32)
        self.held, self.size = [], 0

    def block_rows(self) -> tuple[pa.Array, pa.Array] | None:
        """Columns (block, counts), each block packed; None if nothing was added."""
        self._count()
        if not self.counts.any():
            return None
        return pa.array(range(BLOCKS), pa.int32()), pa.array([zlib.compress(b.tobytes(), 1) for b in np.split(self.counts, BLOCKS)], pa.binary())


def cell(keys: np.ndarray) -> np.ndarray:
    return (keys >> np.uint64(64 - BITS)).astype(np.int64)


def frequency_classes(partial: DataFrame) -> np.ndarray:
    """A class 0 to 40 for each cell: the bit length of its excess over the noise of the rest.

    partial has columns block and counts; BLOCKS sums (32 MB at any input size) come to the driver.
    """

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for block, counts in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                one = np.frombuffer(zlib.decompress(counts.as_buffer()), np.uint32).astype(np.uint64)
                sums[block] = sums[block] + one if block in sums else one
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["block", "counts"])

    count = np.zeros((BLOCKS, (1 << BITS) // BLOCKS), np.uint64)
    for row in partial.select("block", "counts").repartition("block").mapInArrow(total, "block int, counts binary").collect():
        count[row.block] += np.frombuffer(row.counts, np.uint64)
    flat = count.ravel().astype(np.float64)
    noise = np.median(flat)
    return np.ceil(np.log2(np.maximum(0, flat - noise - 3 * np.sqrt(noise) - 1) + 1)).astype(np.uint8)
