"""Functions for SQL users: temporary SQL functions, vectorised UDFs, a grouped aggregate and a table function."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@lru_cache(maxsize=2)
def _piece_model(path: str):
    import sentencepiece

    if not path:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    return sentencepiece.SentencePieceProcessor(model_file=path)


def pieces(path: str = ""):
    """A vectorised UDF: text to the pieces of a sentencepiece model (a public one unless a path is given)."""

    @F.pandas_udf("array<string>")
    def cut(text: pd.Series) -> pd.Series:
        return pd.Series(_piece_model(path).encode(text.tolist(), out_type=str))

    return cut


def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two vectors; 0 if one is the zero vector, null if one is null."""

    def one(x, y):
        if x is None or y is None:
            return None
        x, y = np.asarray(x, float), np.asarray(y, float)
        n = np.linalg.norm(x) * np.linalg.norm(y)
        return float(x @ y / n) if n else 0.0

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")


def rotary(v: pd.Series, position: pd.Series) -> pd.Series:
    """Rotation of component pairs (j, j + half) by position, base 10,000."""

    def one(x, p):
        x = np.asarray(x, float)
        half = len(x) // 2
        angle = p * 10_000.0 ** (-np.arange(half) / half)
        a, b = x[:half], x[half:]
        return np.concatenate([a * np.cos(angle) - b * np.sin(angle), a * np.sin(angle) + b * np.cos(angle)]).tolist()

    return pd.Series([one(x, p) for x, p in zip(v, position, strict=True)])


def far_share(p: pd.Series, q: pd.Series, i: pd.Series, k: pd.Series) -> float:
    """Share of attention that goes k or more back, over a group of cells of one row or window."""
    total = p.sum()
    return float(p[i <= q - k].sum() / total) if total else 0.0


class WindowSpans:
    """window_spans(n, L): one row per window of a document of n tokens."""

    def eval(self, n: int, L: int):
        if n is None or n < L:
            return
        count = -(-n // L)
        half = count // 2
        at = [j * L for j in range(half)] + ([(n - L) // 2] if count % 2 else []) + [n - (half - j) * L for j in range(half)]
        yield from enumerate(at)


SQL_FUNCTIONS = {
    "farspan_window_count(n BIGINT, L BIGINT) RETURNS BIGINT": "CASE WHEN n >= L THEN CEIL(n / L) ELSE 0 END",
    "farspan_starts(n BIGINT, L BIGINT) RETURNS ARRAY<BIGINT>": """CASE WHEN n < L THEN CAST(ARRAY() AS ARRAY<BIGINT>) ELSE CONCAT(
 TRANSFORM(FILTER(SEQUENCE(0L, CAST(CEIL(n / L) AS BIGINT)), j -> j < FLOOR(CEIL(n / L) / 2)), j -> j * L),
 CASE WHEN CEIL(n / L) % 2 = 1 THEN ARRAY(CAST(FLOOR((n - L) / 2) AS BIGINT)) ELSE CAST(ARRAY() AS ARRAY<BIGINT>) END,
 TRANSFORM(FILTER(SEQUENCE(0L, CAST(CEIL(n / L) AS BIGINT)), j -> j < FLOOR(CEIL(n / L) / 2)), j -> n - (CAST(FLOOR(CEIL(n / L) / 2) AS BIGINT) - j) * L)) END""",
    "farspan_lds(ds_z DOUBLE, du_z DOUBLE, alpha DOUBLE) RETURNS DOUBLE": "ds_z + alpha * du_z",
}


def columns() -> dict:
    """The vectorised functions for the DataFrame API (they need a running session to be made)."""
    return {"cosine": F.pandas_udf(cosine, "double"), "rotary": F.pandas_udf(rotary, "array<double>"), "far_share": F.pandas_udf(far_share, "double")}


def register(spark: SparkSession) -> None:
    """All of the above under their names in SQL (a temporary function can't stand inside explode: project it first)."""
    for name, f in columns().items():
        spark.udf.register(name, f)
    spark.udtf.register("window_spans", F.udtf(WindowSpans, returnType="ord: int, start: bigint"))
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
