"""Language identification of mixed text: script ranges narrow the candidates of each word, byte-trigram models
score the word, and a Viterbi pass with a penalty for switching labels spans.

All documents of a chunk go through the Viterbi recursion together, one word position after another.  The models
are fitted on about ``per_language`` documents of each language at most (chosen by a hash of the id), for all
languages there are; the table of scores has MODEL_BYTES at most, so with more than 256 languages each has fewer
cells.  Labelling covers every row and whole texts.

A null text, or one without a letter (Unicode categories L*), is ``und`` with score 0; so is every text if nothing
could be learned.  Words without a letter are neutral; letters of no listed script count as script "Other".  The score
is the share of letters in spans of the predicted language.
Ties go to the language that sorts first.  Repeated rows are labelled alike; an empty table gives an empty
result; columns other than id and text are not read for a prediction.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import lean_batches, texts
from farspan.llm.textbatch import CHUNK_BYTES, LOWER, TextChunk, all_chunks

CELLS = 1 << 16
MODEL_BYTES = 64 << 20
SWITCH_PENALTY = 6.0
WORD_FLOOR = 8.0
CHUNK = 4 << 20

#: First code points of script ranges; a range ends where the next begins. Letters in "" are of no listed script.
SCRIPT_STARTS = [
    (0x0, ""), (0x41, "Latin"), (0x5B, ""), (0x61, "Latin"), (0x7B, ""), (0xAA, "Latin"), (0xAB, ""), (0xB5, "Latin"), (0xB6, ""), (0xBA, "Latin"), (0xBB, ""), (0xC0, "Latin"), (0xD7, ""), (0xD8, "Latin"), (0xF7, ""), (0xF8, "Latin"),
    (0x250, "Latin"), (0x2B0, ""), (0x370, "Greek"), (0x400, "Cyrillic"), (0x530, "Armenian"), (0x590, "Hebrew"), (0x600, "Arabic"), (0x700, "Syriac"), (0x750, "Arabic"), (0x780, "Other"), (0x900, "Devanagari"), (0x980, "Bengali"), (0xA00, "Gurmukhi"), (0xA80, "Gujarati"), (0xB00, "Oriya"), (0xB80, "Tamil"), (0xC00, "Telugu"), (0xC80, "Kannada"), (0xD00, "Malayalam"), (0xD80, "Sinhala"), (0xE00, "Thai"), (0xE80, "Lao"), (0xF00, "Tibetan"), (0x1000, "Myanmar"), (0x10A0, "Georgian"), (0x1100, "Hangul"), (0x1200, "Ethiopic"), (0x13A0, "Other"), (0x1780, "Khmer"), (0x1800, "Mongolian"), (0x18B0, "Other"), (0x1E00, "Latin"), (0x1F00, "Greek"), (0x2000, ""), (0x2C00, "Other"), (0x2E00, ""), (0x3041, "Kana"), (0x3100, "Han"), (0x3130, "Hangul"), (0x3190, ""), (0x3400, "Han"), (0x4DC0, ""), (0x4E00, "Han"), (0xA000, "Other"), (0xAC00, "Hangul"), (0xD7B0, "Other"), (0xE000, ""), (0xF900, "Han"), (0xFB00, "Latin"), (0xFB13, "Other"), (0xFB50, "Arabic"), (0xFE00, ""), (0xFE70, "Arabic"), (0xFEFF, ""), (0xFF21, "Latin"), (0xFF3B, ""), (0xFF41, "Latin"), (0xFF5B, ""), (0xFF66, "Kana"), (0xFFA0, "Hangul"), (0xFFE0, ""), (0x10000, "Other"), (0x1F000, ""), (0x20000, "Han"), (0x323B0, ""),
]
SCRIPTS = sorted({s for _, s in SCRIPT_STARTS if s})
_STARTS = np.array([c for c, _ in SCRIPT_STARTS])
_SCRIPT_OF_RANGE = np.array([SCRIPTS.index(s) if s else -1 for _, s in SCRIPT_STARTS], np.int8)


def code_points(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of first bytes, and the code points there."""
    at = np.flatnonzero((data & 0xC0) != 0x80)
    lead = data[at].astype(np.int64)
    padded = np.concatenate([data, np.zeros(3, np.uint8)]).astype(np.int64)
    one, two, three = (padded[at + j] & 0x3F for j in (1, 2, 3))
    point = np.where(lead < 0x80, lead, np.where(lead < 0xE0, (lead & 0x1F) << 6 | one, np.where(lead < 0xF0, (lead & 0x0F) << 12 | one << 6 | two, (lead & 0x07) << 18 | one << 12 | two << 6 | three)))
    return at, point


@lru_cache(maxsize=1)
def letter_scripts() -> np.ndarray:
    """For every code point its script, -1 if it is no letter."""
    script = np.repeat(_SCRIPT_OF_RANGE, np.diff([*_STARTS.tolist(), 0x110000]))
    script[script < 0] = SCRIPTS.index("Other")
    script[~np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)] = -1
    return script


def scripts_of(points: np.ndarray) -> np.ndarray:
    return letter_scripts()[np.minimum(points, 0x10FFFF)]


class Words:
    """Words of a chunk with their script (-1: no letter), number of letters, and trigram cells."""

    def __init__(self, chunk: TextChunk):
        self.start, self.end, self.first = chunk.words()
        data = LOWER[chunk.data]
        after_c3 = np.concatenate([[False], chunk.data[:-1] == 0xC3]) if len(data) else np.zeros(0, bool)
        capital = after_c3 & (data >= 0x80) & (data <= 0x9E) & (data != 0x97)
        data[capital] += 0x20
        self.data = data
        at, points = code_points(chunk.data)
        script = scripts_of(points)
        lettered = np.flatnonzero(script >= 0)
        word = np.searchsorted(self.start, at[lettered], "right") - 1
        self.letters = np.bincount(word, minlength=len(self.start))[: len(self.start)].astype(np.int64)
        self.script = np.full(len(self.start), -1, np.int8)
        self.script[word[::-1]] = script[lettered][::-1]  # the first letter decides

    def cells(self, number: int = CELLS) -> tuple[np.ndarray, np.ndarray]:
        """Trigram cells (below ``number``, a power of two) of all words end to end, each word between two blanks, and where a word's cells begin."""
        size = self.end - self.start
        begin = np.cumsum(size) - size
        word = np.repeat(np.arange(len(size)), size)
        inner = np.arange(len(word)) - begin[word]
        at = self.start[word] + inner
        data = self.data
        middle = data[at].astype(np.uint32)
        before = np.where(inner > 0, data[np.maximum(at - 1, 0)], 0x20).astype(np.uint32)
        behind = np.where(inner < size[word] - 1, data[np.minimum(at + 1, max(0, len(data) - 1))], 0x20).astype(np.uint32)
        mixed = (before * np.uint32(0x9E3779B1)) ^ (middle * np.uint32(0x85EBCA6B)) ^ (behind * np.uint32(0xC2B2AE35))
        mixed ^= mixed >> np.uint32(15)
        return ((mixed * np.uint32(0x2C1B3C6D)) >> np.uint32(33 - number.bit_length())).astype(np.int64), begin


@dataclass(frozen=True)
class LanguageModel:
    languages: list[str]
    scores: np.ndarray  # (languages, cells), log-probabilities
    allowed: np.ndarray  # (scripts, languages): may a word of the script be of the language


def fit(df: DataFrame, per_language: int = 4_000, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    """Trigram and script counts of the languages; (cells + scripts) counts a language come to the driver, all within MODEL_BYTES * 2."""
    rows = lean_batches(df).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("lang is not null and text is not null")
    size = rows.groupBy("lang").agg(F.count("*").alias("n"))
    languages = sorted(r.lang for r in size.select("lang").collect())
    if not languages:
        return LanguageModel([], np.zeros((0, CELLS)), np.zeros((len(SCRIPTS), 0), bool))
    cells_each = CELLS
    while cells_each > 16 and 4 * cells_each * len(languages) > MODEL_BYTES:
        cells_each //= 2
    part = size.select("lang", F.ceil(1_000_000 * F.least(F.lit(1.0), per_language / F.col("n"))).alias("part"))
    sample = rows.join(F.broadcast(part), "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.col("part")).select("lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for part, chunk in all_chunks(batches):
            words = Words(chunk)
            cells, begin = words.cells(cells_each)
            edge = np.concatenate([begin, [len(cells)]])
            lang = part.column(0).to_pylist()
            for d, (a, b) in enumerate(zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True)):
                own = total.setdefault(lang[d], np.zeros(cells_each + len(SCRIPTS), np.int64))
                own[:cells_each] += np.bincount(cells[edge[a] : edge[b]], minlength=cells_each)
                script = words.script[a:b]
                own[cells_each:] += np.bincount(script[script >= 0], minlength=len(SCRIPTS))
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([x.tobytes() for x in total.values()], pa.binary())], names=["lang", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            for lang, counts in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                one = np.frombuffer(counts.as_buffer(), np.int64)
                sums[lang] = sums[lang] + one if lang in sums else one
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums)), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["lang", "counts"])

    counts = np.zeros((len(languages), cells_each + len(SCRIPTS)))
    number = {x: i for i, x in enumerate(languages)}
    for row in sample.mapInArrow(run, "lang string, counts binary").repartition("lang").mapInArrow(add, "lang string, counts binary").collect():
        counts[number[row.lang]] += np.frombuffer(row.counts, np.int64)
    grams, scripts = counts[:, :cells_each], counts[:, cells_each:]
    scores = np.log(grams + 0.1) - np.log(grams.sum(axis=1, keepdims=True) + 0.1 * cells_each)
    share = scripts / np.maximum(1, scripts.sum(axis=1, keepdims=True))
    return LanguageModel(languages, scores.astype(np.float32), (share >= 0.002).T)


def emissions(model: LanguageModel, words: Words) -> np.ndarray:
    """(words, languages): log-scores relative to the word's best candidate, at least -WORD_FLOOR."""
    cells, begin = words.cells(max(16, model.scores.shape[1]))
    out = np.zeros((len(begin), len(model.languages)), np.float32)
    if out.size:
        for i in range(out.shape[1]):
            out[:, i] = np.add.reduceat(model.scores[i][cells], begin)
        may = model.allowed[words.script]
        may[~may.any(axis=1)] = True
        out[~may] = -np.inf
        out -= out.max(axis=1, keepdims=True)
        np.maximum(out, -WORD_FLOOR, out=out)
        out[words.script < 0] = 0
    return out


def viterbi(score: np.ndarray, first: np.ndarray, penalty: float) -> np.ndarray:
    """Best label of every word, for all texts at once; a label change between two words costs ``penalty``."""
    n = np.diff(first)
    label = np.zeros(len(score), np.int32)
    order = np.argsort(-n, kind="stable")
    begin, length = first[:-1][order], n[order]
    active_at = np.searchsorted(-length, -np.arange(1, (length[0] if len(length) else 0) + 1), "right")
    stay = np.ones(score.shape, bool)
    jump = np.zeros(len(score), np.int32)
    best = np.zeros((len(n), score.shape[1]), np.float64)
    for t, active in enumerate(active_at.tolist()):
        at = begin[:active] + t
        now = best[:active]
        if t:
            top = now.argmax(axis=1)
            other = now[np.arange(active), top] - penalty
            keep = now >= other[:, None]
            stay[at], jump[at] = keep, top
            now[:] = np.maximum(now, other[:, None])
        now += score[at]
        now -= now.max(axis=1, keepdims=True)
    state = best.argmax(axis=1).astype(np.int32)
    for t in range(len(active_at) - 1, -1, -1):
        active = active_at[t]
        at = begin[:active] + t
        own = state[:active]
        label[at] = own
        state[:active] = np.where(stay[at, own], own, jump[at])
    return label


def labelled(model: LanguageModel, batches: Iterator[pa.RecordBatch], penalty: float, text_col: str = "text") -> Iterator[tuple[pa.RecordBatch, list[str], np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, language and score of each text, label of each word, index of each text's first word, number of letters of
    each text in words of a script that a learned language uses).

    Words are scored in small chunks, smaller for many languages; the recursion runs over several of them at once, as
    it is cheaper the more texts go side by side.
    """
    number = len(model.languages)
    limit = max(1 << 12, CHUNK_BYTES * 8 // max(8, number))
    held: list[tuple[pa.RecordBatch, Words, np.ndarray, np.ndarray]] = []
    size, most = 0, max(limit, CHUNK * 4 // max(4, number))

    def resolve() -> tuple[pa.RecordBatch, list[str], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        rows = pa.Table.from_batches([h[0] for h in held]).combine_chunks().to_batches()[0]
        counts = np.concatenate([np.diff(h[1].first) for h in held])
        first = np.concatenate([[0], np.cumsum(counts)])
        letters_of, learned_of = np.concatenate([h[1].letters for h in held]), np.concatenate([h[3] for h in held])
        label = viterbi(np.concatenate([h[2] for h in held]), first, penalty) if number else np.zeros(first[-1], np.int32)
        texts_of, n = np.repeat(np.arange(len(counts)), counts), len(counts)
        total = np.bincount(texts_of, letters_of, n)
        learned = np.bincount(texts_of, letters_of * learned_of, n)
        # letters by text and label, only where there are some
        pair, at = np.unique(texts_of * max(1, number) + label, return_inverse=True)
        letters = np.bincount(at, letters_of, len(pair))
        best = np.lexsort((pair, -letters, pair // max(1, number)))
        top = best[np.unique(pair[best] // max(1, number), return_index=True)[1]]
        chosen, most_letters = np.zeros(n, np.int64), np.zeros(n)
        chosen[pair[top] // max(1, number)], most_letters[pair[top] // max(1, number)] = pair[top] % max(1, number), letters[top]
        known = (total > 0) & (number > 0)
        lang = [model.languages[c] if k else "und" for c, k in zip(chosen.tolist(), known.tolist(), strict=True)]
        return rows, lang, np.where(known, most_letters / np.maximum(total, 1), 0.0), label, first, learned

    for part, chunk in all_chunks(batches, text_col, limit):
        words = Words(chunk)
        learned = (words.script >= 0) & model.allowed.any(axis=1)[words.script] if number else np.zeros(len(words.script), bool)
        held.append((part, words, emissions(model, words), learned))
        words.data = None  # no longer needed
        size += len(chunk.data)
        if size >= most:
            yield resolve()
            held, size = [], 0
    if held:
        yield resolve()


def identify(df: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", with_spans: bool = False, penalty: float = SWITCH_PENALTY) -> DataFrame:
    """(doc_id, lang_pred, score) of every row; ``with_spans`` adds array<struct<start, end, lang>> over word numbers."""
    held = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = held.value
        for rows, lang, score, label, first, _ in labelled(own, batches, penalty):
            columns = [rows.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64())]
            if with_spans:
                spans = []
                for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
                    cut = [0, *(np.flatnonzero(np.diff(label[a:b])) + 1).tolist(), b - a] if b > a and own.languages else [0]
                    spans.append([{"start": x, "end": y, "lang": own.languages[label[a + x]]} for x, y in zip(cut[:-1], cut[1:], strict=True)])
                columns.append(pa.array(spans, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())]))))
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "lang_pred", "score", "spans"][: len(columns)])

    schema = "doc_id long, lang_pred string, score double" + (", spans array<struct<start: int, end: int, lang: string>>" if with_spans else "")
    return texts(df, id_col, text_col).mapInArrow(run, schema)


def with_known_language(df: DataFrame, model: LanguageModel, text_col: str = "text", penalty: float = SWITCH_PENALTY) -> DataFrame:
    """The rows of df, whole, that have a language: a letter, and a word in a script that some learned language uses.
    Mixed texts stay."""
    held = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = held.value
        for rows, lang, _, _, _, learned in labelled(own, batches, penalty, text_col):
            yield rows.filter(pa.array([x != "und" and n > 0 for x, n in zip(lang, learned.tolist(), strict=True)], pa.bool_()))

    return lean_batches(df).mapInArrow(run, df.schema)
