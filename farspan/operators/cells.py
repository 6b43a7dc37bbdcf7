"""Reference paths: attention cell by cell, as a relation for small data, and in arrays of a few windows at a time.

Production scoring is ``score.score_windows``.  The relation (``cells`` and what stands on it) exists to be read and to
check the arrays; ``window_scores`` and ``cumulative_row`` make the same cells where a window is, and none of them leaves.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from farspan.operators.batches import coded, of_one_length
from farspan.sources.intermediate import lean_batches

#: Cells that the relation agrees to make.
MOST_CELLS = 50_000_000
#: Cells in memory at a time.
HELD_CELLS = 1 << 18
_ROW = ["doc_id", "category", "start", "q"]


def cells(windows: DataFrame, D: int = 16, spread: float = 4.6) -> DataFrame:
    """attn_cells (doc_id, category, start, len, q, i, p), q and i from 1, under the hexdot profile."""
    count = windows.agg(F.sum(F.col("len").cast("long") * (F.col("len") + 1) / 2)).first()[0] or 0
    if count > MOST_CELLS:
        raise ValueError(f"{count:.0f} cells are too many for the reference path; use score.score_windows")
    digits = F.transform(F.sequence(F.lit(1), F.lit(D)), lambda j: (F.instr(F.lit("0123456789abcdef"), F.substr(F.md5("tok"), j, F.lit(1))) - 8.5) / spread)
    toks = windows.select("doc_id", "category", "start", "len", F.posexplode("toks").alias("at", "tok")).select("doc_id", "category", "start", "len", (F.col("at") + 1).alias("at"), digits.alias("v"))
    q = toks.select("doc_id", "category", "start", "len", F.col("at").alias("q"), F.col("v").alias("vq"))
    i = toks.select("doc_id", "start", F.col("at").alias("i"), F.col("v").alias("vi"))
    dot = F.aggregate(F.zip_with("vq", "vi", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    met = q.join(i, ["doc_id", "start"]).where(F.col("i") <= F.col("q")).withColumn("w", F.exp(dot / F.sqrt(F.lit(float(D)))))
    row = Window.partitionBy("doc_id", "start", "q")
    return met.withColumn("p", F.col("w") / F.sum("w").over(row)).select("doc_id", "category", "start", "len", "q", "i", "p")


def cumulative(attn: DataFrame) -> DataFrame:
    """Attention of q on the first m tokens, for every m."""
    up_to = Window.partitionBy("doc_id", "start", "q").orderBy("i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return attn.select("doc_id", "category", "start", "len", "q", F.col("i").alias("m"), F.sum("p").over(up_to).alias("a"))


def strengths(attn: DataFrame, k: int) -> DataFrame:
    """Strength of each token: attention at least k back, 0 where nothing lies that far."""
    far = F.when(F.col("i") <= F.col("q") - k, F.col("p"))
    return attn.groupBy(*_ROW, "len").agg(F.coalesce(F.sum(far), F.lit(0.0)).alias("ds_q"), F.coalesce(F.sum(far * far), F.lit(0.0)).alias("s2_q"), F.sum("p").alias("row_sum"))


def scores(attn: DataFrame, k: int) -> DataFrame:
    """Window scores from the cells: the mean of the token strengths, the far block's sum over L, and minus its variance."""
    rows = strengths(attn, k)
    n = (F.col("len") - k) * (F.col("len") - k + 1) / 2
    out = rows.groupBy("doc_id", "category", "start", "len").agg(F.avg("ds_q").alias("ds"), F.sum("ds_q").alias("block"), F.sum("s2_q").alias("squares"), F.max(F.abs(F.col("row_sum") - 1)).alias("off"))
    mean = F.col("block") / n
    du = F.when(F.col("len") > k, -F.greatest(F.lit(0.0), F.col("squares") / n - mean * mean)).otherwise(0.0)
    return out.select("doc_id", "category", "start", "len", "ds", (F.col("block") / F.col("len")).alias("ds_block"), du.alias("du"), "off")


def _vectors(words: list[str], D: int, spread: float) -> np.ndarray:
    raw = np.frombuffer(b"".join(hashlib.md5(w.encode()).digest() for w in words), np.uint8).reshape(-1, 16)
    return (np.stack([raw >> 4, raw & 15], axis=2).reshape(-1, 32)[:, :D] - 7.5) / spread


def _rows_of_cells(v: np.ndarray, a: int, b: int) -> np.ndarray:
    """p (windows, rows a to b, columns 0 to b - 1), 0 behind the diagonal, of windows whose tokens have vectors v."""
    w = np.exp(v[:, a:b] @ v[:, :b].transpose(0, 2, 1) / np.sqrt(v.shape[2]))
    w *= np.arange(b)[None, :] <= np.arange(a, b)[:, None]
    return w / w.sum(axis=2, keepdims=True)


def _scored(v: np.ndarray, k: int) -> dict[str, np.ndarray]:
    n, L, _ = v.shape
    far, squares, off = np.zeros((n, L)), np.zeros((n, L)), np.zeros(n)
    step = max(1, HELD_CELLS // max(1, n * L))
    for a in range(0, L, step):
        b = min(L, a + step)
        p = _rows_of_cells(v, a, b)
        off = np.maximum(off, np.abs(p.sum(axis=2) - 1).max(axis=1))
        p *= np.arange(b)[None, :] <= np.arange(a, b)[:, None] - k
        far[:, a:b], squares[:, a:b] = p.sum(axis=2), (p * p).sum(axis=2)
    count = (L - k) * (L - k + 1) / 2
    du = -np.maximum(0.0, squares.sum(axis=1) / count - (far.sum(axis=1) / count) ** 2) if L > k else np.zeros(n)
    return {"ds": far.mean(axis=1), "ds_block": far.sum(axis=1) / L, "du": du, "off": off}


def _in_arrays(windows: DataFrame, compute, columns: dict[str, tuple[str, pa.DataType]], D: int, spread: float) -> DataFrame:
    """doc_id, category, start, len and what compute(vectors of windows of one length) gives, for every window with tokens."""
    keys = {"doc_id": "long", "category": "string", "start": "long"}
    schema = ", ".join(f"{n} {t}" for n, t in (keys | {"len": "int"} | {n: t for n, (t, _) in columns.items()}).items())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words, codes, ends = coded(batch.column(3))
            vectors = _vectors(words, D, spread)
            for rows, at in of_one_length(codes, ends, 1 << 12):
                n, L = at.shape
                if L:
                    found = compute(vectors[at])
                    held = [batch.column(i).take(pa.array(rows)) for i in range(3)] + [pa.array(np.full(n, L, np.int32))]
                    yield pa.RecordBatch.from_arrays(held + [pa.array(list(found[c]) if found[c].ndim > 1 else found[c], t) for c, (_, t) in columns.items()], names=[*keys, "len", *columns])

    return lean_batches(windows).select(F.col("doc_id").cast("long"), "category", F.col("start").cast("long"), "toks").mapInArrow(run, schema)


def window_scores(windows: DataFrame, k: int, D: int = 16, spread: float = 4.6) -> DataFrame:
    """``scores(cells(windows), k)`` for any number of windows: a map, with HELD_CELLS cells in a task (a row at least)."""
    return _in_arrays(windows, lambda v: _scored(v, k), {c: ("double", pa.float64()) for c in ("ds", "ds_block", "du", "off")}, D, spread)


def cumulative_row(windows: DataFrame, q: int, D: int = 16, spread: float = 4.6) -> DataFrame:
    """Row q (from 1) of ``cumulative(cells(windows))`` for any number of windows; no other row is made."""

    def compute(v: np.ndarray) -> dict[str, np.ndarray]:
        return {"upto": np.cumsum(_rows_of_cells(v, q - 1, q)[:, 0], axis=1)}

    rows = _in_arrays(windows.where(F.size("toks") >= q), compute, {"upto": ("array<double>", pa.list_(pa.float64()))}, D, spread)
    return rows.select("doc_id", "category", "start", "len", F.lit(q).alias("q"), F.posexplode("upto").alias("at", "a")).select("doc_id", "category", "start", "len", "q", (F.col("at") + 1).alias("m"), "a")
