"""Suffix order of a block of bytes, one bucket at a time, with long ties cut short by a difference cover.

Sample positions are those whose residue modulo v lies in a cover D, so that for any two positions some
offset below v brings both onto sample positions.  The samples are ranked once; then the suffixes of one
leading byte after another are sorted by their first v bytes only, and ties are decided by the sample ranks
at the common offset.  Only one bucket and the sample ranks are held beside the block.
"""

from __future__ import annotations

from functools import cmp_to_key

import numpy as np

MODULUS = 31


def difference_cover(v: int) -> list[int]:
    """A small set whose pairwise differences hit every residue modulo v, found greedily."""
    cover, missing = [0], set(range(1, v))
    while missing:
        best = max((c for c in range(v) if c not in cover), key=lambda c: (len(missing & {(c - d) % v for d in cover} | missing & {(d - c) % v for d in cover}), -c))
        missing -= {(best - d) % v for d in cover} | {(d - best) % v for d in cover}
        cover.append(best)
    return sorted(cover)


def _offsets(v: int, cover: list[int]) -> np.ndarray:
    """offsets[r, s]: the least offset that brings residues r and s into the cover together."""
    inside = np.isin(np.arange(v), cover)
    out = np.zeros((v, v), np.int64)
    for r in range(v):
        for s in range(v):
            out[r, s] = next(x for x in range(v) if inside[(r + x) % v] and inside[(s + x) % v])
    return out


COVER = difference_cover(MODULUS)
OFFSETS = _offsets(MODULUS, COVER)


def words_at(block: np.ndarray, pad: int) -> np.ndarray:
    """For every position its next eight bytes as one big-endian number; zeros follow the block."""
    data = np.concatenate([block, np.zeros(pad + 8, np.uint8)]).astype(np.uint64)
    out = np.zeros(len(data) - 7, np.uint64)
    for j in range(8):
        out |= data[j : j + len(out)] << np.uint64(56 - 8 * j)
    return out


def _names(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Order of rows by the keys (first key counts most), and their dense ranks in that order (equal rows share one)."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    for k in keys:
        ranked = k[order]
        new[1:] |= ranked[1:] != ranked[:-1]
    rank = np.empty(len(order), np.int64)
    rank[order] = np.cumsum(new)
    return order, rank


def sample_ranks(words: np.ndarray, n: int, depth: int) -> np.ndarray:
    """Ranks (from 1) of the sample positions by at least ``depth`` bytes; 0 elsewhere and behind the block."""
    v = MODULUS
    inside = np.isin(np.arange(v), COVER)
    at = np.flatnonzero(inside[np.arange(n) % v])
    ranks = np.zeros(n + depth + 4 * v, np.int64)
    if len(at) == 0:
        return ranks
    mask = np.uint64(0xFFFFFFFFFFFFFF00)  # 31 bytes are three full words and seven bytes of the fourth
    _, rank = _names([words[at], words[at + 8], words[at + 16], words[at + 24] & mask])
    ranks[at] = rank + 1
    reached = v
    while reached < depth:
        _, rank = _names([ranks[at], ranks[at + reached]])
        ranks[at] = rank + 1
        reached *= 2
    return ranks


def suffix_order(block: np.ndarray, positions: np.ndarray, depth: int) -> np.ndarray:
    """``positions`` in the lexicographic order of what follows them in ``block``, compared to ``depth`` bytes or more."""
    v, n = MODULUS, len(block)
    words = words_at(block, depth + 5 * v)
    ranks = sample_ranks(words, n, depth)
    mask = np.uint64(0xFFFFFFFFFFFFFF00)
    by_bucket = positions[np.argsort(block[positions], kind="stable")]
    edges = np.flatnonzero(np.concatenate([[True], np.diff(block[by_bucket].astype(np.int16)) != 0])) if len(by_bucket) else np.zeros(0, np.int64)
    out = np.empty_like(by_bucket)
    for a, b in zip(edges.tolist(), [*edges[1:].tolist(), len(by_bucket)], strict=True):
        own = by_bucket[a:b]
        order, tie = _names([words[own], words[own + 8], words[own + 16], words[own + 24] & mask])
        own, tie = own[order], tie[order]
        residue = own % v
        first = np.flatnonzero(np.concatenate([[True], tie[1:] != tie[:-1]]))
        low, high = np.minimum.reduceat(residue, first), np.maximum.reduceat(residue, first)
        offset = OFFSETS[low, high][tie]
        other = np.add.reduceat((residue != low[tie]) & (residue != high[tie]), first) > 0
        own = own[np.lexsort((ranks[own + offset], tie))]
        for t in np.flatnonzero(other):  # three residues or more: no single offset serves all pairs
            x, y = first[t], first[t + 1] if t + 1 < len(first) else len(own)

            def compare(i: int, j: int) -> int:
                d = OFFSETS[i % v, j % v]
                return int(ranks[i + d] - ranks[j + d])

            own[x:y] = sorted(own[x:y].tolist(), key=cmp_to_key(compare))
        out[a:b] = own
    return out


def equal_classes(block: np.ndarray, ordered: np.ndarray, length: int) -> np.ndarray:
    """A class number for each entry of an ordered list: neighbours whose first ``length`` bytes agree share it."""
    if length < 8:
        raise ValueError("length must be 8 or more")
    words = words_at(block, length + 8)
    same = np.ones(max(0, len(ordered) - 1), bool)
    for j in [*range(0, length - 8, 8), length - 8]:
        w = words[ordered + j]
        same &= w[1:] == w[:-1]
    return np.concatenate([[0], np.cumsum(~same)])[: len(ordered)]
