"""The fused scoring kernel: one pass over blocks of attention rows, never the whole matrix.

For every far distance k it accumulates, over the cells with i <= q - k, their sum and sum of squares and the
strength of each row.  Memory is heads x block x L.
"""

from __future__ import annotations

import time

import numpy as np


def far_cells(L: int, k: int) -> int:
    return max(0, L - k) * (max(0, L - k) + 1) // 2


def token_strengths(profile, tokens: list, ks: list[int], block: int = 128, head_agg: str = "mean", chosen: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    """(strength, squares): per k, head and row the far sum and far sum of squares; and the share of the first token.

    chosen: only these rows (a sorted array); all others stay zero.
    """
    L, state = len(tokens), profile.state(tokens)
    heads = 1 if head_agg == "mean" else profile.heads
    far = np.zeros((len(ks), heads, L))
    squares = np.zeros_like(far)
    sink, seen = 0.0, 0
    for a in range(0, L, block):
        b = min(L, a + block)
        if chosen is not None:
            inside = chosen[(chosen >= a) & (chosen < b)] - a
            if len(inside) == 0:
                continue
            if hasattr(profile, "some_rows"):
                _some(profile, state, inside + a, ks, head_agg, far, squares)
                continue
        p, scale = _block(profile, state, a, b, head_agg)
        sink += (p[:, :, 0] * scale).mean(axis=0).sum()
        seen += b - a
        for j, k in enumerate(ks):
            every, some = max(0, a - k + 1), max(0, b - k)  # columns far from all rows of the block, and from some
            left = p[:, :, :every]
            own, twice = left.sum(axis=2, dtype=np.float64), np.einsum("hqi,hqi->hq", left, left)
            if some > every:
                edge = p[:, :, every:some] * (np.arange(every, some)[None, :] <= (np.arange(a, b) - k)[:, None])
                own, twice = own + edge.sum(axis=2, dtype=np.float64), twice + np.einsum("hqi,hqi->hq", edge, edge)
            far[j, : p.shape[0], a:b] = own * scale
            squares[j, : p.shape[0], a:b] = twice * scale * scale
    return far, squares, float(sink / max(1, seen))


def _block(profile, state, a: int, b: int, head_agg: str) -> tuple[np.ndarray, np.ndarray]:
    """Rows a to b of the heads that count, and a factor for each row: what is summed needs no division cell by cell."""
    if not hasattr(profile, "row_weights"):
        p = profile.rows(state, a, b)
        p = p.mean(axis=0, keepdims=True) if head_agg == "mean" else p[int(head_agg[5:])][None] if head_agg.startswith("head:") else p
        return p, np.ones(p.shape[:2])
    held, total = profile.row_weights(state, a, b)
    if head_agg == "mean" and len(held) > 1:
        return np.einsum("hqi,hq->qi", held, (1 / (len(held) * total)).astype(held.dtype))[None], np.ones((1, b - a))
    if head_agg.startswith("head:"):
        j = int(head_agg[5:])
        held, total = held[j][None], total[j][None]
    return held, 1 / total


def _some(profile, state, rows: np.ndarray, ks: list[int], head_agg: str, far: np.ndarray, squares: np.ndarray) -> None:
    """Far sums of single rows, each computed on its own."""
    p = profile.some_rows(state, rows)
    p = p.mean(axis=0, keepdims=True) if head_agg == "mean" else p[int(head_agg[5:])][None] if head_agg.startswith("head:") else p
    for j, k in enumerate(ks):
        left = p * (np.arange(p.shape[2])[None, :] <= (rows - k)[:, None])
        far[j, : len(p), rows] = left.sum(axis=2).T
        squares[j, : len(p), rows] = np.einsum("hqi,hqi->hq", left, left).T


def strength(far: np.ndarray) -> float:
    """Mean over all tokens of the window (and over heads, if they are kept apart)."""
    return float(far.mean(axis=1).mean()) if far.size else 0.0


def uniformity(far: np.ndarray, squares: np.ndarray, L: int, k: int, over: str = "triangle", ddof: int = 0) -> float:
    """Minus the variance: of the far cells, of the square they lie in (zeros included), or of the token strengths."""
    values = []
    for f, s in zip(far, squares, strict=True):
        if over == "token":
            n, total, twice = L, f.sum(), (f * f).sum()
        else:
            n, total, twice = far_cells(L, k) if over == "triangle" else max(0, L - k) ** 2, f.sum(), s.sum()
        if n - ddof <= 0:
            values.append(0.0)
            continue
        mean = total / n
        values.append(-max(0.0, float(twice / n - mean * mean)) * n / (n - ddof))
    return float(np.mean(values)) + 0.0


def score(profile, tokens: list, ks: list[int], block: int = 128, over: str = "triangle", ddof: int = 0, head_agg: str = "mean") -> list[dict]:
    """One row of raw scores for each k."""
    began, L, out = time.process_time(), len(tokens), []
    far, squares, sink = token_strengths(profile, tokens, ks, block, head_agg) if L else (np.zeros((len(ks), 1, 0)),) * 2 + (0.0,)
    for j, k in enumerate(ks):
        n = far_cells(L, k)
        out.append({"len": L, "k": k, "ds": strength(far[j]), "du": uniformity(far[j], squares[j], L, k, over, ddof), "far_mean": float(far[j].mean(axis=0).sum() / n) if n else 0.0, "far_cells": n, "sink_share": sink, "pair_ops": profile.pair_ops(L, profile.heads, profile.width)})
    spent = (time.process_time() - began) * 1e3
    return [r | {"cpu_ms": spent / max(1, len(ks))} for r in out]


#: Weights of attention in memory at a time, floats of queries that are made together, and the longest windows that are scored together.
HELD, QUERIES, TOGETHER = 1 << 17, 1 << 19, 1024


def strengths_many(profile, words: list[str], codes: np.ndarray, ks: list[int], block: int = 32, first: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``token_strengths`` (mean of the heads) of many windows of one length, whose tokens are numbers of words: far sums and
    sums of squares (ks, windows, L), and each row's share of the first token (windows, L); rows before ``first`` stay zero."""
    n, L = codes.shape
    far = np.zeros((len(ks), n, L))
    squares, sink = np.zeros_like(far), np.zeros((n, L))
    each, room = max(1, QUERIES // max(1, L * profile.heads * profile.width)), {}
    for at in range(0, n, each):
        some = slice(at, at + each)
        _strengths(*profile.states(words, codes[some], room), ks, block, first, far[:, some], squares[:, some], sink[some])
    return far, squares, sink


def _strengths(q: np.ndarray, keys: np.ndarray, small: bool, ks: list[int], block: int, first: int, far: np.ndarray, squares: np.ndarray, sink: np.ndarray) -> None:
    """Fills far, squares and sink from row ``first`` on; heads that share their keys meet them in one product, and rows are
    summed up by products with ones.  Heads are averaged only over the columns that are far from a row of the block: of all
    others the rows' sums take what they need."""
    n, heads, L, width = q.shape
    groups, ones = keys.shape[1], np.ones(L, q.dtype)
    columns = np.ascontiguousarray(keys.transpose(0, 1, 3, 2))  # small products are faster so
    for a in range(first, L, block):
        b = min(L, a + block)
        step, upto = min(n, max(1, HELD // (heads * (b - a) * b))), max(0, b - min(ks, default=b))
        below = (np.arange(b - a)[None, :] <= np.arange(b - a)[:, None]).astype(q.dtype)
        held, asked = np.empty((step, groups, heads // groups * (b - a), b), q.dtype), np.empty((step, heads, b - a, width), q.dtype)
        for i in range(0, n, step):
            m = min(step, n - i)
            np.copyto(asked[:m], q[i : i + m, :, a:b])
            p = np.matmul(asked[:m].reshape(m, groups, -1, width), columns[i : i + m, :, :, :b], out=held[:m]).reshape(m, heads, b - a, b)
            if not small:
                np.copyto(p[..., a:], -np.inf, where=below == 0)
                p -= p.max(axis=3, keepdims=True)
            np.exp(p, out=p)
            total = p[..., :a] @ ones[:a] + np.einsum("nhqi,qi->nhq", p[..., a:], below)
            share = 1 / (heads * total)
            sink[i : i + m, a:b] = np.einsum("nhq,nhq->nq", p[..., 0], share)
            if not upto:
                continue
            if upto > a:
                p[..., a:upto] *= below[:, : upto - a]
            if heads > 1:
                p, scale = np.einsum("nhqi,nhq->nqi", p[..., :upto], share), 1.0
            else:
                p, scale = p[:, 0], share[:, 0].astype(np.float64)
            for j, k in enumerate(ks):
                every, some = max(0, a - k + 1), max(0, b - k)  # columns far from all rows of the block, and from some
                left = p[..., :every]
                own, twice = left @ ones[:every], np.einsum("nqi,nqi->nq", left, left)
                if some > every:
                    edge = p[..., every:some] * (np.arange(every, some)[None, :] <= (np.arange(a, b) - k)[:, None])
                    own, twice = own + edge.sum(axis=2, dtype=np.float64), twice + np.einsum("nqi,nqi->nq", edge, edge)
                far[j, i : i + m, a:b], squares[j, i : i + m, a:b] = own * scale, twice * scale * scale


def uniformities(far: np.ndarray, squares: np.ndarray, L: int, k: int, over: str = "triangle", ddof: int = 0) -> np.ndarray:
    """``uniformity`` of many windows of one length (windows, L), whose heads are averaged."""
    total, twice = far.sum(axis=1), (far * far if over == "token" else squares).sum(axis=1)
    n = L if over == "token" else far_cells(L, k) if over == "triangle" else max(0, L - k) ** 2
    if n - ddof <= 0:
        return np.zeros(len(far))
    mean = total / n
    return -np.maximum(0.0, twice / n - mean * mean) * n / (n - ddof) + 0.0


def _scored(profile, far: np.ndarray, squares: np.ndarray, sink: np.ndarray, ks: list[int], over: str, ddof: int) -> list[list[dict]]:
    """Rows of raw scores for each window, without the CPU time."""
    L, ds, first = far.shape[2], far.mean(axis=2).tolist(), sink.mean(axis=1).tolist()
    du = [uniformities(far[j], squares[j], L, k, over, ddof).tolist() for j, k in enumerate(ks)]
    counts = [far_cells(L, k) for k in ks]
    mean = [(far[j].sum(axis=1) / max(1, c)).tolist() for j, c in enumerate(counts)]
    ops = profile.pair_ops(L, profile.heads, profile.width)
    return [[{"len": L, "k": k, "ds": ds[j][i], "du": du[j][i], "far_mean": mean[j][i] if counts[j] else 0.0, "far_cells": counts[j], "sink_share": first[i], "pair_ops": ops} for j, k in enumerate(ks)] for i in range(len(first))]


def score_many(profile, words: list[str], codes: np.ndarray, ks: list[int], over: str = "triangle", ddof: int = 0) -> list[list[dict]]:
    """``score`` of many windows of one length: a list of rows for each; the CPU time is shared out evenly."""
    began = time.process_time()
    out = _scored(profile, *strengths_many(profile, words, codes, ks), ks, over, ddof)
    spent = (time.process_time() - began) * 1e3 / max(1, len(codes) * len(ks))
    return [[r | {"cpu_ms": spent} for r in rows] for rows in out]


def score_twins(profile, words: list[str], codes: np.ndarray, tails: np.ndarray, ks: list[int], block: int = 32) -> tuple[list[list[dict]], list[list[dict]]]:
    """Raw scores of windows, and of their twins with other last tokens: rows before those are the same and made once."""
    first = (codes.shape[1] - tails.shape[1]) // block * block
    own = strengths_many(profile, words, codes, ks, block)
    twin = strengths_many(profile, words, np.concatenate([codes[:, : codes.shape[1] - tails.shape[1]], tails], axis=1), ks, block, first)
    for x, y in zip(own, twin, strict=True):
        y[..., :first] = x[..., :first]
    return _scored(profile, *own, ks, "triangle", 0), _scored(profile, *twin, ks, "triangle", 0)


def score_sampled(profile, tokens: list, k: int, rows: int, block: int = 64) -> dict:
    """Strength estimated from one row in each of ``rows`` equal strata of the rows that can look far, with its standard error."""
    L = len(tokens)
    if L <= k:
        return {"ds_hat": 0.0, "du_hat": 0.0, "se": 0.0, "rows": 0}
    edges = np.linspace(k, L, min(rows, L - k) + 1)
    chosen = np.unique(((edges[:-1] + edges[1:]) / 2).astype(int))
    far, squares, _ = token_strengths(profile, tokens, [k], max(block, 1024), chosen=chosen)
    f, s, r = far[0, 0, chosen], squares[0, 0, chosen], len(chosen)
    n, weight = far_cells(L, k), (L - k) / r
    mean = f.sum() * weight / n
    step = np.diff(f)
    return {"ds_hat": float((L - k) / L * f.mean()), "du_hat": -max(0.0, float(s.sum() * weight / n - mean * mean)), "se": float((L - k) / L * np.sqrt((step * step).sum() / 2 / max(1, r - 1) / r)), "rows": r}
