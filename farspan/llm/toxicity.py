"""Toxicity by a weighted lexicon.

Text is folded to a skeleton (case, accents, look-alike letters, digits and signs that stand for letters,
invisible characters), and an Aho-Corasick automaton finds the lexicon's stems at word starts.  A stem's weight
is its smoothed log-odds among labelled documents; an exception phrase (a stem with a neighbouring word that
labelled documents show to be harmless) cancels the stem's weight.  The weights found, normalised by length,
go through a logistic curve.

The lexicon, the exceptions and the curve are fitted on at most about ``sample`` labelled rows, chosen by a
hash of the id; scoring covers every row and whole texts.  Null and empty texts score as the curve at zero
weight; repeated rows score alike; without labelled rows of both classes the score is 0 for all; an empty table
gives an empty result; columns other than id and text are not read.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import lean_batches, texts, written

#: Characters that are written for a Latin letter.  "l" and "1" share the skeleton of "i".
LOOKALIKES = {
    "а": "a", "с": "c", "е": "e", "һ": "h", "і": "i", "ј": "j", "к": "k", "м": "m", "о": "o", "р": "p", "ѕ": "s", "т": "t", "у": "y", "х": "x", "ԁ": "d", "ԛ": "q", "ԝ": "w", "ӏ": "i",
    "α": "a", "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ı": "i", "ł": "i", "ø": "o", "ß": "s", "æ": "a", "œ": "o",
    "0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "€": "e", "|": "i", "l": "i",
}
INVISIBLE = (0xAD, *range(0x200B, 0x2010), *range(0x202A, 0x202F), 0x2060, 0xFEFF, *range(0x300, 0x370))


def _folding_table() -> dict[int, str | None]:
    table: dict[int, str | None] = {c: None for c in INVISIBLE}
    ranges = (range(0x21, 0x250), range(0x370, 0x530), range(0x1E00, 0x2000), range(0xFF01, 0xFF5F), range(0x1D400, 0x1D7FF))
    for code in (c for r in ranges for c in r):
        plain = unicodedata.normalize("NFKD", chr(code)).lower()
        plain = "".join(c for c in plain if not unicodedata.combining(c))
        plain = "".join(LOOKALIKES.get(c, c) for c in plain)
        if len(plain) == 1 and plain != chr(code):
            table[code] = plain
    return table | {ord(c): x for c, x in LOOKALIKES.items()}


FOLDING = _folding_table()
_ASCII = {c: x for c, x in FOLDING.items() if c < 128}
WORD = re.compile(r"[^\W\d_]+")
LAST_WORD = regex.compile(r"[^\W\d_]+", regex.REVERSE)
STEM_LENGTHS = range(4, 9)


def fold(text: str) -> str:
    return text.translate(_ASCII if text.isascii() else FOLDING)


def stems(words: set[str]) -> set[str]:
    return {w[:n] for w in words for n in STEM_LENGTHS if len(w) > n} | {w for w in words if len(w) > 2}


@dataclass(frozen=True)
class Lexicon:
    weights: dict[str, float]
    exceptions: frozenset[tuple[str, str, bool]]  # (stem, neighbouring word, does it precede)
    curve: tuple[float, float, float]

    def probability(self, weight: float, words: int) -> float:
        a, b, c = self.curve
        z = a + b * math.log1p(weight) + c * weight / math.sqrt(words + 1)
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


class Matcher:
    def __init__(self, weights: dict[str, float], exceptions: frozenset):
        import ahocorasick

        self.weights, self.exceptions = weights, exceptions
        self.excepted = {s for s, _, _ in exceptions}
        self.automaton = ahocorasick.Automaton()
        for stem in weights:
            self.automaton.add_word(stem, stem)
        self.automaton.make_automaton() if weights else None

    def found(self, folded: str) -> list[tuple[int, str]]:
        """(start, stem) of the longest stem at each word start; one-word entries must fill the word or begin it."""
        if not self.weights:
            return []
        best: dict[int, str] = {}
        for end, stem in self.automaton.iter(folded):
            start = end - len(stem) + 1
            if (start == 0 or not folded[start - 1].isalpha()) and len(stem) > len(best.get(start, "")):
                best[start] = stem
        return list(best.items())

    def weight(self, folded: str) -> float:
        total = 0.0
        for start, stem in self.found(folded):
            if stem in self.excepted:
                before, after = neighbours(folded, start)
                if (stem, before, True) in self.exceptions or (stem, after, False) in self.exceptions:
                    continue
            total += self.weights[stem]
        return total


def neighbours(folded: str, start: int) -> tuple[str, str]:
    """The words before and after the word that starts at ``start``."""
    before = LAST_WORD.search(folded, 0, start)
    own = WORD.match(folded, start)
    after = WORD.search(folded, own.end()) if own else None
    return (before[0] if before else ""), (after[0] if after else "")


def _counted(sample: DataFrame, wanted: dict[str, int] | None, toxic: int) -> DataFrame:
    """Documents of one class that hold each stem."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count: Counter[str] = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                words = set(WORD.findall(fold(text or "")))
                found = stems(words)
                count.update(found if wanted is None else found & wanted.keys())
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(list(count), pa.string()), pa.array(list(count.values()), pa.int64())], names=["stem", "n"])

    return sample.where(F.col("toxic") == toxic).select("text").mapInArrow(run, "stem string, n long").groupBy("stem").agg(F.sum("n").alias("n"))


def choose_stems(toxic: dict[str, int], clean: dict[str, int], n_toxic: int, n_clean: int) -> dict[str, float]:
    """Stems much likelier in toxic documents; a longer stem only where it says clearly more than a shorter one."""

    def odds(s: str) -> float:
        return math.log((toxic[s] + 0.5) / (n_toxic + 1)) - math.log((clean.get(s, 0) + 0.5) / (n_clean + 1))

    def purity(s: str) -> float:
        return toxic[s] / (toxic[s] + clean.get(s, 0))

    def surprise(s: str) -> float:
        """How far the toxic share of a stem's documents lies above the share of all, in standard deviations."""
        n, rate = toxic[s] + clean.get(s, 0), n_toxic / (n_toxic + n_clean)
        return (toxic[s] - n * rate) / math.sqrt(n * rate * (1 - rate))

    likely = [s for s in toxic if purity(s) >= 0.5 and odds(s) >= 1 and surprise(s) >= 4.5]
    chosen: dict[str, float] = {}
    for s in sorted(likely, key=lambda s: (len(s), s)):
        shorter = [s[:n] for n in range(3, len(s)) if s[:n] in chosen]
        if not shorter or purity(s) > purity(shorter[-1]) + 0.1:
            chosen[s] = odds(s)
    return dict(sorted(chosen.items(), key=lambda x: (-x[1] * toxic[x[0]], x[0])))


def fit_curve(weight: np.ndarray, words: np.ndarray, toxic: np.ndarray) -> tuple[float, float, float]:
    """Ridge logistic regression by Newton steps."""
    x = np.stack([np.ones(len(weight)), np.log1p(weight), weight / np.sqrt(words + 1)], axis=1)
    beta, ridge = np.zeros(3), np.diag([1e-3, 1e-2, 1e-2])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p) + 1e-9)[:, None]) + ridge, x.T @ (toxic - p) - ridge @ beta)
        beta += step
        if np.abs(step).max() < 1e-8:
            break
    return float(beta[0]), float(beta[1]), float(beta[2])


def fit(df: DataFrame, labels: DataFrame, sample: int = 20_000) -> Lexicon:
    """Lexicon from documents and their labels (doc_id, toxic 0/1).

    About ``sample`` labelled rows at most are used.  Stems that stand in a hundredth of the toxic ones come to the
    driver: no more than a hundred times the stems of a mean document.
    """
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    rows = marks.count()
    drawn = marks.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < math.ceil(1_000_000 * min(1.0, sample / max(1, rows))))
    chosen = written(texts(df).join(F.broadcast(drawn), "doc_id").select("text", "toxic"), "toxicity")
    size = {r.toxic: r["count"] for r in chosen.groupBy("toxic").count().collect()}
    if len(size) < 2:
        return Lexicon({}, frozenset(), (-30.0, 0.0, 0.0))
    least = max(5, size[1] // 100)
    toxic = {r.stem: r.n for r in _counted(chosen, None, 1).where(F.col("n") >= least).collect()}
    clean = {r.stem: r.n for r in _counted(chosen, toxic, 0).collect()}
    weights = choose_stems(toxic, clean, size[1], size[0])

    def phrases(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher, count = Matcher(weights, frozenset()), Counter()
        for batch in batches:
            for text, mark in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                folded, own = fold(text or ""), set()
                for start, stem in matcher.found(folded):
                    before, after = neighbours(folded, start)
                    own |= {(stem, before, True), (stem, after, False)}
                count.update((*x, mark) for x in own if x[1])
        if count:
            s, w, f, t = zip(*count, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(w), pa.array(f), pa.array(t, pa.int32()), pa.array(list(count.values()), pa.int64())], names=["stem", "word", "first", "toxic", "n"])

    n, t = F.sum("n"), F.sum(F.when(F.col("toxic") == 1, F.col("n")).otherwise(0))
    harmless = chosen.mapInArrow(phrases, "stem string, word string, first boolean, toxic int, n long").groupBy("stem", "word", "first").agg(n.alias("n"), t.alias("t")).where("n - t >= 5 and 10 * t <= n")
    exceptions = frozenset((r.stem, r.word, r.first) for r in harmless.collect())

    def weighed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(weights, exceptions)
        for batch in batches:
            folded = [fold(x or "") for x in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([matcher.weight(x) for x in folded], pa.float64()), pa.array([len(x.split()) for x in folded], pa.int64()), batch.column(1)], names=["weight", "words", "toxic"])

    points = chosen.mapInArrow(weighed, "weight double, words long, toxic int").toPandas().sort_values(["weight", "words", "toxic"])
    return Lexicon(weights, exceptions, fit_curve(points["weight"].to_numpy(), points["words"].to_numpy(), points["toxic"].to_numpy()))


def score(df: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score, weight) for every row."""
    model = df.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = model.value
        matcher = Matcher(own.weights, own.exceptions)
        for whole in batches:
            for a in range(0, whole.num_rows, 500):
                batch = whole.slice(a, 500)
                weights, scores = [], []
                for text in batch.column(1).to_pylist():
                    folded = fold(text or "")
                    weights.append(matcher.weight(folded))
                    scores.append(own.probability(weights[-1], len(folded.split())))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64()), pa.array(weights, pa.float64())], names=["doc_id", "score", "weight"])

    return texts(df, id_col, text_col).mapInArrow(run, "doc_id long, score double, weight double")


def without_toxic(df: DataFrame, lexicon: Lexicon, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """The rows of df, whole, whose text scores below the threshold."""
    model, at = df.sparkSession.sparkContext.broadcast(lexicon), df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = model.value
        matcher = Matcher(own.weights, own.exceptions)
        for whole in batches:
            for a in range(0, whole.num_rows, 500):
                batch = whole.slice(a, 500)
                folded = [fold(t or "") for t in batch.column(at).to_pylist()]
                keep = [own.probability(matcher.weight(t), len(t.split())) < threshold for t in folded]
                yield batch.filter(pa.array(keep, pa.bool_()))

    return lean_batches(df).mapInArrow(run, df.schema)
