"""Token lists of many rows as numbers: words are looked at once a batch, whatever their occurrences."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def coded(lists: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(words, codes, ends): the distinct words of an array of token lists, the number of each token's word, all lists one
    after the other, and where each list ends in them (a null list is empty)."""
    flat = lists.flatten().dictionary_encode()
    lengths = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)
    return flat.dictionary.to_pylist(), flat.indices.to_numpy(zero_copy_only=False).astype(np.int64), np.cumsum(lengths, dtype=np.int64)


def of_one_length(codes: np.ndarray, ends: np.ndarray, cells: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, their codes as a matrix): lists of the same length together, at most ``cells`` tokens (one list at least)."""
    lengths = np.diff(ends, prepend=0)
    for L in np.unique(lengths):
        rows, step = np.flatnonzero(lengths == L), max(1, cells // max(1, int(L)))
        for a in range(0, len(rows), step):
            some = rows[a : a + step]
            yield some, codes[(ends[some] - L)[:, None] + np.arange(L)]
