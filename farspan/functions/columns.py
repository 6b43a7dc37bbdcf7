"""Expressions that stay inside the JVM: tokenising, window starts in closed form, deterministic random order."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"


def tokens(text: Column, mode: str = "word") -> Column:
    """array<string> of a text's tokens; a null or blank text has none.

    word: runs without white space; wordpunct: words and single marks; char: code points; utf8: bytes as hex pairs;
    lines: words, with U+2029 behind the last one of a line.
    """
    text = F.coalesce(text, F.lit(""))
    if mode == "word":
        return F.regexp_extract_all(text, F.lit(WORD), F.lit(0))
    if mode == "wordpunct":
        return F.regexp_extract_all(text, F.lit(r"[\p{L}\p{N}_]+|[^\p{L}\p{N}_\x20\x09-\x0D]"), F.lit(0))
    if mode == "char":
        return F.filter(F.split(text, ""), lambda c: c != "")
    if mode == "utf8":
        return F.regexp_extract_all(F.hex(F.encode(text, "utf-8")), F.lit("[0-9A-F]{2}"), F.lit(0))
    if mode == "lines":
        return tokens(F.regexp_replace(text, r"([^\x20\x09-\x0D])[\x20\x09-\x0D]*\n[\x20\x09-\x0D]*", "$1\u2029 "))
    if mode.startswith("hash"):  # hash(V): words as numbers below V
        size = int(mode[5:-1])
        return F.transform(tokens(text), lambda t: F.pmod(F.conv(F.substring(F.md5(t), 1, 8), 16, 10).cast("bigint"), F.lit(size)).cast("string"))
    raise ValueError(f"unknown token mode {mode}")


def starts(n: Column, L: int, middle: str = "centre") -> Column:
    """Start offsets of the windows of a document of n tokens, in closed form and ascending order.

    With c = ceil(n / L) windows: half of them from the front, half from the back, and for an odd count one in the
    middle ('centre', or 'left_aligned' to the front ones).  Fewer than L tokens give no window.
    """
    n = n.cast("long")
    count = F.ceil(n / F.lit(L)).cast("long")
    half = F.floor(count / 2).cast("long")
    none = F.array().cast("array<bigint>")
    steps = F.when(half > 0, F.sequence(F.lit(0).cast("long"), half - 1)).otherwise(none)
    front = F.transform(steps, lambda j: j * L)
    back = F.transform(steps, lambda j: n - (half - j) * L)
    centre = F.floor((n - L) / 2) if middle == "centre" else half * L
    mid = F.when(count % 2 == 1, F.array(centre.cast("long"))).otherwise(none)
    return F.when(n >= L, F.concat(front, mid, back)).otherwise(none)


def shuffle_key(seed: int, *ids: Column) -> Column:
    """A fixed pseudo-random order: md5 of the seed and the identifiers."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[x.cast("string") for x in ids]))


def scaled(x: Column, digits: int) -> Column:
    """x in units of 10**-digits as a whole number, so that summation order can't show."""
    return F.round(x * F.lit(float(10**digits))).cast("bigint")
