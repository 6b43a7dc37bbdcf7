"""Risk-controlled quality rules.

Every document gets whole-text counts and a handful of badness ratios in [0, 1].  The labelled documents are dealt into
two parts by a hash of their id.  From the first part (a third, all strata together) follows a path: for each rule and
cut-off the share of bad documents among those it rejects, so that a level between 1 and 0 stands for one cut-off of
each rule, and falling LEVELS tighten all rules together.  The second part is the holdout: in every stratum the levels
are tested in that order on the stratum's own labels, and one passes while the exact binomial tail shows that the rules
together reject at most ``risk`` of its good documents.  Tests in a fixed order need no correction among themselves,
and the confidence is divided by the number of strata, so all guarantees hold together with probability 1 - delta: in
every stratum at most ``risk`` of the good documents are rejected by the rules.  Of the levels that pass, the one with
the best difference of caught and lost shares is used.

A stratum whose holdout has too few good labels to certify even a level that loses none (``labels_needed``; 86 at the
defaults with four strata) rejects nothing by these rules.  Any number of strata is calibrated, by a grouped
aggregation; nothing but their number and the path (rules x BINS counts) comes to the driver.

Null and empty texts have zero counts and fail the base rule (fewer than 50 words).  Repeated rows are judged
each on their own; an empty label table leaves the base rule alone; other columns of df are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import BROADCAST_ROWS, lean_batches, written
from farspan.llm.textbatch import IS_SPACE, TextChunk, all_chunks, mix64, word_shingles

LEVELS = (0.95, 0.9, 0.85, 0.8, 0.75, 0.7, 0.65, 0.6, 0.55, 0.5, 0.45, 0.4, 0.35, 0.3, 0.25, 0.2, 0.15, 0.1)
BINS = 64
#: Of the labelled documents, one in so many shapes the path; the others are the holdout.
PATH_PART = 3
RULES = ("symbols", "repeated_lines", "repeated_words", "capitals", "shouting", "long_words")

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_CONTINUES = np.zeros(256, bool)
_CONTINUES[0x80:0xC0] = True


def _sums(mask: np.ndarray, off: np.ndarray) -> np.ndarray:
    total = np.zeros(len(mask) + 1, np.int64)
    np.cumsum(mask, out=total[1:])
    return total[off[1:]] - total[off[:-1]]


def _group_sizes(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each key how often it occurs, and whether the entry is its first."""
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    new = np.concatenate([[True], ranked[1:] != ranked[:-1]]) if len(key) else np.zeros(0, bool)
    group = np.cumsum(new) - 1
    size, first = np.empty(len(key), np.int64), np.empty(len(key), bool)
    size[order] = np.bincount(group)[group] if len(key) else 0
    first[order] = new
    return size, first


def counts(chunk: TextChunk) -> dict[str, np.ndarray]:
    """Exact whole-text counts of each document of a chunk."""
    data, off = chunk.data, chunk.off
    start, end, first = chunk.words()
    n_words = np.diff(first)
    code_point = ~_CONTINUES[data]
    word_chars = _sums(code_point & ~IS_SPACE[data], off)
    # repeated 3-word windows: a word counts if any window over it occurs twice or more in its text
    shingle, at = word_shingles(chunk.span_hash(start, end), first, 3)
    text_of = np.repeat(np.arange(len(chunk)), np.diff(at))
    size, _ = _group_sizes(mix64(shingle ^ mix64(text_of.astype(np.uint64) + np.uint64(1))))
    twice = np.flatnonzero((size > 1) & (n_words[text_of] >= 3))
    begin = first[:-1][text_of[twice]] + twice - at[:-1][text_of[twice]]
    covered = np.zeros(len(start) + 3, bool)
    for j in range(3):
        covered[begin + j] = True
    n_repeat = _sums(covered[: len(start)], first)
    # lines
    ls, le, lf = chunk.lines()
    inked = np.searchsorted(start, le) > np.searchsorted(start, ls)
    line_text = np.repeat(np.arange(len(chunk)), np.diff(lf))
    held = np.flatnonzero(inked)
    _, is_first = _group_sizes(mix64(chunk.span_hash(ls[held], le[held]) ^ mix64(line_text[held].astype(np.uint64) + np.uint64(1))))
    n_dup = np.bincount(line_text[held], ~is_first, len(chunk)).astype(np.int64)
    n_lines = np.bincount(line_text[held], minlength=len(chunk)).astype(np.int64)
    upper = _sums((data >= 65) & (data <= 90), off)
    lower = _sums((data >= 97) & (data <= 122), off)
    chars = np.zeros(len(data) + 1, np.int64)
    np.cumsum(code_point, out=chars[1:])
    longest = np.zeros(len(chunk), np.int64)
    if len(start):
        full = np.flatnonzero(n_words > 0)
        longest[full] = np.maximum.reduceat(chars[end] - chars[start], first[:-1][full])
    return {"n_words": n_words, "word_chars": word_chars, "n_symbols": _sums(_SYMBOL[data], off), "n_dup_lines": n_dup, "n_repeat_words": n_repeat, "n_lines": n_lines, "n_upper": upper, "n_lower": lower, "n_shouts": _sums(data == 33, off), "longest_word": longest}


COUNT_NAMES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_lower", "n_shouts", "longest_word")


def measure(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str | None = "lang") -> DataFrame:
    """doc_id, stratum and the counts of every row of df."""
    stratum = F.coalesce(F.col(stratum_col).cast("string"), F.lit("")) if stratum_col else F.lit("")
    source = lean_batches(df).select(F.col(id_col).cast("long").alias("doc_id"), stratum.alias("stratum"), F.col(text_col).cast("string").alias("text"))
    names = ["doc_id", "stratum", *COUNT_NAMES]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, chunk in all_chunks(batches):
            found = counts(chunk)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(found[n]) for n in COUNT_NAMES)], names=names)

    return source.mapInArrow(run, "doc_id long, stratum string, " + ", ".join(f"{n} long" for n in COUNT_NAMES))


def ratios() -> dict[str, F.Column]:
    """Badness of a document under each rule, 0 to 1."""

    def share(part: F.Column, whole: F.Column) -> F.Column:
        return F.when(whole > 0, F.least(F.lit(1.0), part / whole)).otherwise(0.0)

    c = F.col
    return {
        "symbols": share(c("n_symbols"), c("n_words") + c("n_symbols")),
        "repeated_lines": share(c("n_dup_lines"), c("n_lines")),
        "repeated_words": share(c("n_repeat_words"), c("n_words")),
        "capitals": share(c("n_upper"), c("n_upper") + c("n_lower")),
        "shouting": share(c("n_shouts"), c("n_words")),
        "long_words": F.when(c("longest_word") > 0, 1 - 1 / (1 + c("longest_word") / 64.0)).otherwise(0.0),
    }


def binomial_tail(k: int, n: int, p: float) -> float:
    """P(X <= k) for X ~ Binomial(n, p), summed exactly in logarithms."""
    if k >= n or p <= 0:
        return 1.0
    if p >= 1:
        return 0.0
    base, lp, lq = math.lgamma(n + 1), math.log(p), math.log1p(-p)
    terms = [base - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * lp + (n - i) * lq for i in range(k + 1)]
    top = max(terms)
    return min(1.0, math.exp(top) * math.fsum(math.exp(t - top) for t in terms))


def labels_needed(risk: float, level: float) -> int:
    """Good labels without which no test can pass: (1 - risk) ** n <= level."""
    return math.ceil(math.log(level) / math.log1p(-risk))


def choose_step(good: list[int], bad: list[int], risk: float, level: float) -> int | None:
    """The step to use, None if no step is certified or none does any good.

    good, bad: labelled documents by the first step that rejects them; the last entry counts those that no step rejects.
    The exact upper bound of the false rejection rate at confidence 1 - level is below ``risk`` just if
    P(Binomial(n, risk) <= k) <= level.
    """
    n, m, k, caught, best, most = sum(good), sum(bad), 0, 0, None, 0.0
    for i in range(len(good) - 1):
        k, caught = k + good[i], caught + bad[i]
        if n == 0 or binomial_tail(k, n, risk) > level:
            break
        if m and caught / m - k / n > most:
            best, most = i, caught / m - k / n
    return best


def bins() -> dict[str, F.Column]:
    """Bin of each ratio, finer near 0; bin 0 is that of ratio 0 alone."""
    return {r: F.when(v > 0, F.least(F.lit(BINS - 1), F.floor(F.sqrt(v) * (BINS - 1)) + 1)).otherwise(0).cast("int") for r, v in ratios().items()}


def for_path() -> F.Column:
    return F.pmod(F.xxhash64("doc_id"), F.lit(PATH_PART)) == 0


def path_scores(measured: DataFrame, marks: DataFrame) -> dict[str, list[float]]:
    """For each rule and bin the best share of bad documents among those that a cut-off there or below rejects."""
    each = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), v.alias("bin")) for r, v in bins().items()])).alias("x")
    cells = measured.join(marks.where(for_path()), "doc_id").select("good", each).groupBy("x.rule", "x.bin", "good").count().collect()
    table = {r: np.zeros((2, BINS), np.int64) for r in RULES}
    for c in cells:
        table[c.rule][c.good, c.bin] += c["count"]
    scores = {}
    for r, (bad, good) in table.items():
        tail_bad, tail_all = bad[::-1].cumsum()[::-1], (bad + good)[::-1].cumsum()[::-1]
        share = tail_bad / (tail_all + 1)
        share[0] = 0
        scores[r] = np.maximum.accumulate(share).tolist()
    return scores


def severity(scores: dict[str, list[float]], measured: DataFrame) -> DataFrame:
    """measured with ``step``, the first level that rejects the row (len(LEVELS) if none does), and ``rule``, which rule does so."""
    per = F.array(*[F.struct(F.element_at(F.array(*map(F.lit, scores[r])), v + 1).alias("score"), F.lit(-i).alias("at"), F.lit(r).alias("rule")) for i, (r, v) in enumerate(bins().items())])
    marked = measured.withColumn("worst", F.array_max(per))
    step = F.size(F.filter(F.array(*map(F.lit, LEVELS)), lambda x: x > F.col("worst.score")))
    return marked.select(*measured.columns, step.alias("step"), F.col("worst.rule").alias("rule"))


def calibrate(stepped: DataFrame, marks: DataFrame, risk: float = 0.05, delta: float = 0.05) -> DataFrame:
    """(stratum, allowed): the last step whose rejections hold, for strata that have one; tested on the holdout, stratum by stratum."""
    cells = stepped.select("doc_id", "stratum", "step").join(marks.where(~for_path()), "doc_id").groupBy("stratum", "step", "good").count()
    level = delta / max(1, cells.select("stratum").distinct().count())
    steps = len(LEVELS) + 1

    def choose(rows: pd.DataFrame) -> pd.DataFrame:
        good, bad = [0] * steps, [0] * steps
        for step, mark, n in zip(rows["step"], rows["good"], rows["count"], strict=True):
            (good if mark else bad)[step] += n
        chosen = choose_step(good, bad, risk, level)
        return pd.DataFrame([(rows["stratum"].iloc[0], chosen)] if chosen is not None else [], columns=["stratum", "allowed"])

    return cells.groupBy("stratum").applyInPandas(choose, "stratum string, allowed int")


def base_failed() -> F.Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def judge(df: DataFrame, labels: DataFrame, risk: float = 0.05, delta: float = 0.05, stratum_col: str | None = "lang") -> DataFrame:
    """The counts of every row, kept, and the rule that rejected it (null if none did): calibrated on the labelled rows.

    Of several labels of a document the worst counts.  Steps are broadcast if there are at most BROADCAST_ROWS strata.
    """
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("good")).where("doc_id is not null and good in (0, 1)").groupBy("doc_id").agg(F.min("good").alias("good"))
    measured = written(measure(df, stratum_col=stratum_col), "quality")
    stepped = severity(path_scores(measured, marks), measured)
    allowed = written(calibrate(stepped, marks, risk, delta), "quality-steps")
    held = F.broadcast(allowed) if allowed.count() <= BROADCAST_ROWS else allowed
    out = stepped.join(held, "stratum", "left").withColumn("base_failed", base_failed())
    rejected = F.when(F.col("step") <= F.col("allowed"), F.col("rule"))
    return out.select(*measured.columns, "base_failed", rejected.alias("rejected_by"), (~F.col("base_failed") & rejected.isNull()).alias("kept"))
