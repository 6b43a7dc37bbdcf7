"""Document likelihood by subword lattices.

The vocabulary's scores weight every segmentation of every word, and they alone speak for words that training never
held.  For words that it held, the lattice has one more arc with the word's own frequency; on most texts that arc
decides (README has figures), so this is a lattice model with learned words rather than one of the vocabulary alone.

Every word is a lattice over its bytes (behind one blank): an arc for each vocabulary piece, so that a path is a
segmentation.  Arc weights start from the scores of an existing vocabulary (a piece of rank r gets weight
1 / (r + RANK_SHIFT)) and are re-estimated by forward-backward expectation over the distinct words of the training
documents, with the existing scores as prior.  Beside the subword paths, a word seen in training has one arc that
spans it whole, with absolutely discounted weight; the discounted mass weighs the subword paths.  The log-space
forward recursion sums all paths: the result is the marginal probability of the word.

Documents come from classes (a column of the training rows, at most MAX_CLASSES values and the rest), each with
its own weights; inside a document words are drawn by a Polya urn whose base is the class's lattice, so that a word
used once is likelier afterwards.  A document's probability is the sum over classes of prior, urn and end.  All
weights are proper, so documents' probabilities sum to at most one.  Scoring reads only the text.

Words are counted in tasks, then by a shuffle on their 64-bit hash; a word's lattice is evaluated once.  Documents
meet the words' values in two ways: the HEAD most frequent words at most are broadcast (a threshold is chosen from
a histogram of counts so that they fit), all others are joined by a shuffle.

Null and empty texts consist of their end only.  Repeated rows are counted and scored each on their own; an empty
table gives an empty result; without training rows words are scored by the vocabulary alone; other columns are
not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farspan.llm.storage import lean_batches, written
from farspan.llm.textbatch import IS_SPACE, LOWER, TextChunk, all_chunks, signed

RANK_SHIFT = 10.0
BYTE_WEIGHT = 1e-6
PRIOR_WORDS = 1_000.0
DISCOUNT = 0.75
ROUNDS = 2
#: Share of a class's spare mass that goes to words of all classes before the lattice.
SHARED = 0.15
#: Strength of the base in a document's urn, in words.
URN = 3_000.0
MAX_CLASSES = 7
#: Words whose values are broadcast, at most (16 bytes and 8 for each class).
HEAD = 1 << 19
#: Distinct words that a task gathers before it passes their counts on.
GATHERED = 400_000
_CELLS = 1 << 19
LOG10 = math.log(10)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class Pieces:
    """Byte strings of a vocabulary with prior log-weights; one arc for every single byte is guaranteed."""

    def __init__(self, path: str | None = None):
        import sentencepiece

        held = sentencepiece.SentencePieceProcessor(model_file=path or default_vocabulary())
        weight: dict[bytes, float] = {bytes([b]): BYTE_WEIGHT for b in range(256)}
        for i in range(held.get_piece_size()):
            if held.is_control(i) or held.is_unknown(i) or held.is_byte(i) or held.is_unused(i):
                continue
            raw, score = held.id_to_piece(i).replace("▁", " ").encode(), held.get_score(i)
            if b" " not in raw[1:] and score > -1e6:
                weight[raw] = max(weight.get(raw, 0.0), 1 / (max(0.0, -score) + RANK_SHIFT))
        self.texts = sorted(weight, key=lambda b: (len(b), b))
        total = sum(weight.values())
        self.prior = np.log(np.array([weight[t] for t in self.texts]) / total)
        self.longest = max(map(len, self.texts))
        flat = TextChunk(np.frombuffer(b"".join(self.texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in self.texts])]))
        hashes = flat.span_hash(flat.off[:-1], flat.off[1:])
        self.order = np.argsort(hashes)
        self.hashes = hashes[self.order]
        self.maybe = np.zeros(1 << 20, bool)  # most substrings are no piece: seen here before they are looked up
        self.maybe[hashes >> np.uint64(44)] = True

    def number(self, hashes: np.ndarray) -> np.ndarray:
        """Piece number of each hash, or len(texts) where none has it."""
        out = np.full(len(hashes), len(self.texts), np.int32)
        hit = np.flatnonzero(self.maybe[hashes >> np.uint64(44)])
        wanted = hashes[hit]
        at = np.searchsorted(self.hashes, wanted)
        at[at == len(self.hashes)] = 0
        out[hit] = np.where(self.hashes[at] == wanted, self.order[at], len(self.texts))
        return out


class Lattices:
    """Lattices of words of one byte length (with the blank), as piece numbers of all arcs."""

    def __init__(self, pieces: Pieces, words: list[bytes], length: int):
        self.length, self.n = length, len(words)
        chunk = TextChunk(np.frombuffer(b"".join(words), np.uint8), np.arange(len(words) + 1) * length)
        base = chunk.off[:-1][:, None]
        self.arcs = []
        for size in range(1, min(pieces.longest, length) + 1):
            start = base + np.arange(length - size + 1)
            self.arcs.append(pieces.number(chunk.span_hash(start.ravel(), (start + size).ravel())).reshape(start.shape))
        # sizes of the arcs that start at each place in any of the words
        there = [(a < len(pieces.texts)).any(axis=0) for a in self.arcs]
        self.leaving = [[s for s in range(1, min(len(there), length - i) + 1) if there[s - 1][i]] for i in range(length)]
        self.entering = [[s for s in range(1, min(len(there), j) + 1) if there[s - 1][j - s]] for j in range(length + 1)]

    def forward(self, weight: np.ndarray) -> np.ndarray:
        """Log of the summed weight of all paths to each place; weight has a last entry of -inf for missing arcs."""
        alpha = np.full((self.n, self.length + 1), -np.inf)
        alpha[:, 0] = 0
        for j in range(1, self.length + 1):
            into = np.stack([alpha[:, j - s] + weight[self.arcs[s - 1][:, j - s]] for s in self.entering[j]])
            top = into.max(axis=0)
            alpha[:, j] = top + np.log(np.exp(into - top).sum(axis=0))
        return alpha

    def expected(self, weight: np.ndarray) -> np.ndarray:
        """Expected number of uses of each piece, summed over the words."""
        alpha = self.forward(weight)
        beta = np.full_like(alpha, -np.inf)
        beta[:, -1] = 0
        total = alpha[:, -1]
        uses = np.zeros(len(weight))
        for i in range(self.length - 1, -1, -1):
            sizes = self.leaving[i]
            number = np.stack([self.arcs[s - 1][:, i] for s in sizes])
            out = np.stack([beta[:, i + s] for s in sizes]) + weight[number]
            top = out.max(axis=0)
            beta[:, i] = top + np.log(np.exp(out - top).sum(axis=0))
            share = np.exp(alpha[:, i] + out - total)
            uses += np.bincount(number.ravel(), share.ravel(), len(weight))
        uses[-1] = 0
        return uses


def by_length(words: list[bytes], pieces: Pieces) -> Iterator[tuple[np.ndarray, Lattices]]:
    """Portions of words of one length, each with the places of its words in the list."""
    size = np.array([len(w) for w in words]) + 1
    for length in np.unique(size).tolist():
        own = np.flatnonzero(size == length)
        step = max(1, _CELLS // (length * min(length, pieces.longest)))
        for a in range(0, len(own), step):
            at = own[a : a + step]
            yield at, Lattices(pieces, [b" " + words[i] for i in at.tolist()], length)


def word_hashes(chunk: TextChunk) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    start, end, first = chunk.words()
    return start, end, first, chunk.span_hash(start, end, lower=True)


def log_gamma(x: np.ndarray) -> np.ndarray:
    """For x >= 1: Stirling's series, six steps up."""
    y = x + 6
    series = (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5)
    return series - np.log(x * (x + 1) * (x + 2) * (x + 3) * (x + 4) * (x + 5))


def _log_gamma(x: Column) -> Column:
    """The same over a column."""
    y = x + 6
    series = (y - 0.5) * F.ln(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5)
    return series - sum((F.ln(x + i) for i in range(1, 6)), F.ln(x))


def count_words(rows: DataFrame, classes: int) -> DataFrame:
    """(h, word, total, seen_0, ..): occurrences of each lower-cased word in all rows, and in training rows by class.

    rows: class (its number, -1 for rows that aren't learned from) and text.
    """
    seen = [f"seen_{z}" for z in range(classes)]

    def counted_in(chunk: TextChunk, label: np.ndarray) -> tuple[np.ndarray, np.ndarray, pa.Array]:
        start, end, first, h = word_hashes(chunk)
        of = np.repeat(label, np.diff(first))
        order = np.argsort(h)
        ranked, of = h[order], of[order]
        at = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
        counts = np.stack([np.diff(np.concatenate([at, [len(h)]])), *(np.add.reduceat((of == z).astype(np.int64), at) for z in range(classes))])
        one = order[at]
        size = end[one] - start[one]
        offset = np.concatenate([[0], np.cumsum(size)])
        source = np.arange(offset[-1]) + np.repeat(start[one] - offset[:-1], size)
        words = pa.Array.from_buffers(pa.binary(), len(one), [None, pa.py_buffer(offset.astype(np.int32)), pa.py_buffer(LOWER[chunk.data[source]])])
        return ranked[at], counts, words

    def merged(parts: list[tuple[np.ndarray, np.ndarray, pa.Array]]) -> pa.RecordBatch:
        h = np.concatenate([p[0] for p in parts])
        order = np.argsort(h, kind="stable")
        at = np.flatnonzero(np.concatenate([[True], h[order][1:] != h[order][:-1]]))
        counts = np.add.reduceat(np.concatenate([p[1] for p in parts], axis=1)[:, order], at, axis=1)
        words = pa.concat_arrays([p[2] for p in parts]).take(pa.array(order[at]))
        return pa.RecordBatch.from_arrays([pa.array(signed(h[order[at]])), words, *map(pa.array, counts)], names=["h", "word", "total", *seen])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, size = [], 0
        for part, chunk in all_chunks(batches):
            if IS_SPACE[chunk.data].all():
                continue
            parts.append(counted_in(chunk, part.column(0).to_numpy()))
            size += len(parts[-1][0])
            if size >= GATHERED:
                yield merged(parts)
                parts, size = [], 0
        if parts:
            yield merged(parts)

    counted = rows.select("class", "text").mapInArrow(run, "h long, word binary, total long, " + ", ".join(f"{c} long" for c in seen))
    return counted.groupBy("h").agg(F.first("word").alias("word"), *[F.sum(c).alias(c) for c in ("total", *seen)])


def estimate(words: DataFrame, classes: int, vocabulary: str | None, rounds: int) -> np.ndarray:
    """(classes, pieces + 1) log-weights from the distinct training words; one number a piece and class comes to the driver."""
    pieces = Pieces(vocabulary)
    weight = np.tile(np.append(pieces.prior, -np.inf), (classes, 1))
    prior = np.exp(pieces.prior)
    spark = words.sparkSession
    shape = weight.shape
    for _ in range(rounds):
        held = spark.sparkContext.broadcast(weight)

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            own, uses = Pieces(vocabulary), np.zeros(shape)
            for batch in batches:
                for z in range(classes):
                    mine = batch.column(0).filter(pc.greater(batch.column(1 + z), 0))
                    for a in range(0, len(mine), 20_000):
                        for _, lattices in by_length(mine.slice(a, 20_000).to_pylist(), own):
                            uses[z] += lattices.expected(held.value[z])
            if uses.any():
                yield pa.RecordBatch.from_arrays([pa.array([0]), pa.array([uses.tobytes()])], names=["k", "uses"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = None
            for batch in batches:
                for one in batch.column(1):
                    x = np.frombuffer(one.as_buffer(), np.float64)
                    total = x if total is None else total + x
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([0]), pa.array([total.tobytes()])], names=["k", "uses"])

        partial = words.select("word", *[f"seen_{z}" for z in range(classes)]).mapInArrow(run, "k long, uses binary").repartition(4).mapInArrow(add, "k long, uses binary")
        uses = sum((np.frombuffer(r.uses, np.float64) for r in partial.collect()), np.zeros(weight.size)).reshape(shape)[:, :-1]
        weight = np.concatenate([np.log((uses + PRIOR_WORDS * prior) / (uses.sum(axis=1, keepdims=True) + PRIOR_WORDS)), np.full((classes, 1), -np.inf)], axis=1)
    return weight


def word_values(words: DataFrame, weight: np.ndarray, vocabulary: str | None, tokens: list[int], types: list[int]) -> DataFrame:
    """(h, total, seen, s_0, ..): natural logs of each word's marginal probability in each class."""
    held = words.sparkSession.sparkContext.broadcast(weight)
    classes, everywhere = len(weight), max(1, sum(tokens))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces(vocabulary)
        for whole in batches:
            for a in range(0, whole.num_rows, 20_000):
                batch = whole.slice(a, 20_000)
                paths = np.empty((classes, batch.num_rows))
                for at, lattices in by_length(batch.column(1).to_pylist(), pieces):
                    for z in range(classes):
                        paths[z, at] = lattices.forward(held.value[z])[:, -1]
                seen = [batch.column(3 + z).to_numpy().astype(np.float64) for z in range(classes)]
                total = sum(seen)
                with np.errstate(divide="ignore"):
                    shared = np.log(SHARED * total / everywhere)
                    back = np.logaddexp(shared, math.log(1 - SHARED) + paths)
                    values = [np.logaddexp(np.log(np.maximum(x - DISCOUNT, 0) / max(1, n)), (math.log(DISCOUNT * v / n) if n else 0.0) + b) for x, n, v, b in zip(seen, tokens, types, back, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(total.astype(np.int64)), *map(pa.array, values)], names=["h", "total", "seen", *(f"s_{z}" for z in range(classes))])

    return words.select("h", "word", "total", *[f"seen_{z}" for z in range(classes)]).mapInArrow(run, "h long, total long, seen long, " + ", ".join(f"s_{z} double" for z in range(classes)))


def head_threshold(values: DataFrame, most: int) -> int:
    """A power of two such that at most ``most`` words occur so often."""
    bucket = F.floor(F.log2(F.col("total"))).cast("int")
    count = {r.b: r.n for r in values.groupBy(bucket.alias("b")).agg(F.count("*").alias("n")).collect()}
    above, b = 0, 63
    while b > 0 and above + count.get(b - 1, 0) <= most:
        b -= 1
        above += count.get(b, 0)
    return 2**b


def score_documents(df: DataFrame, train: Column, class_col: str | None = None, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text", rounds: int = ROUNDS, head: int = HEAD, urn: float | None = None) -> DataFrame:
    """(doc_id, train, n_tokens, n_known, train_tokens, base_score, score) for every row of df; scores in log10.

    ``train``: condition over df's columns; rows where it holds are learned from, with their class if class_col is given.
    """
    spark, urn = df.sparkSession, URN if urn is None else urn
    label = F.coalesce(F.col(class_col).cast("string"), F.lit("")) if class_col else F.lit("")
    rows = lean_batches(df).select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(train, F.lit(False)).alias("train"), label.alias("label"), F.col(text_col).cast("string").alias("text"))
    ranked = rows.where("train").groupBy("label").count().orderBy(F.desc("count"), "label")
    size = [(r.label, r["count"]) for r in ranked.limit(MAX_CLASSES).collect()]
    rest = rows.where("train").count() - sum(n for _, n in size)
    ends = [n for _, n in size] + [rest] * (rest > 0) or [0]
    classes = len(ends)
    number = F.lit(classes - 1)
    for z, (name, _) in enumerate(size):
        number = F.when(F.col("label") == name, z).otherwise(number)
    rows = rows.select("doc_id", "train", F.when(F.col("train"), number).otherwise(-1).cast("int").alias("class"), "text")
    words = written(count_words(rows, classes), "words")
    seen = [F.col(f"seen_{z}") for z in range(classes)]
    sums = words.agg(*[F.coalesce(F.sum(c), F.lit(0)) for c in seen], *[F.count_if(c > 0) for c in seen], F.count_if(sum(seen, F.lit(0)) > 0)).first()
    tokens, types = [sums[z] + ends[z] for z in range(classes)], [sums[classes + z] + (ends[z] > 0) for z in range(classes)]
    all_ends, all_tokens, all_types = sum(ends), sum(tokens), sums[2 * classes] + (sum(ends) > 0)
    weight = estimate(words, classes, vocabulary, rounds)
    values = written(word_values(words, weight, vocabulary, tokens, types), "word-values")
    least = head_threshold(values, head)
    names = [f"s_{z}" for z in range(classes)]
    top = values.where(F.col("total") >= least).select("h", "seen", *names).toArrow()
    order = np.argsort(top["h"].to_numpy())
    frequent = spark.sparkContext.broadcast((top["h"].to_numpy()[order], top["seen"].to_numpy()[order], np.stack([top[c].to_numpy()[order] for c in names])))
    floor, log_urn = math.log10(all_tokens + all_types + 1), math.log(urn)
    end_base = math.log10(all_ends + 1) - floor
    end_score = [math.log(e / n) + log_urn if e else log_urn for e, n in zip(ends, tokens, strict=True)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        top_h, top_seen, top_score = frequent.value
        top_base = np.log10(top_seen + 1.0) - floor
        row_number = TaskContext.get().partitionId() << 40
        columns = ["row", "doc_id", "train", "h", "n", "known", "base", *names]
        for part, chunk in all_chunks(batches):
            _, _, first, hashes = word_hashes(chunk)
            n = np.diff(first)
            text = np.repeat(np.arange(len(n)), n)
            order = np.lexsort((hashes, text))
            h, text = hashes[order], text[order]
            new = np.concatenate([[True], (h[1:] != h[:-1]) | (text[1:] != text[:-1])]) if len(h) else np.zeros(0, bool)
            once = np.flatnonzero(new)
            c = np.diff(np.concatenate([once, [len(h)]]))
            h, text = signed(h[once]), text[once]
            at = np.searchsorted(top_h, h)
            at[at == len(top_h)] = 0
            found = top_h[at] == h if len(top_h) else np.zeros(len(h), bool)
            own, value, times = text[found], at[found], c[found]
            known = np.bincount(own, times * (top_seen[value] > 0), len(n)).astype(np.int64) + (all_ends > 0)
            base = np.bincount(own, times * top_base[value], len(n)) + end_base
            again = np.flatnonzero(times > 1)
            scores = []
            for z in range(classes):
                log_p = top_score[z][value]
                gain = log_p + log_urn
                mass = np.exp(gain[again])
                gain[again] += log_gamma(times[again] + mass) - log_gamma(1 + mass)
                scores.append(np.bincount(own, gain, len(n)) + end_score[z])
            row = row_number + np.arange(len(n))
            row_number += len(n)
            yield pa.RecordBatch.from_arrays([pa.array(row), part.column(0), part.column(1), pa.nulls(len(n), pa.int64()), pa.array(n + 1), pa.array(known), pa.array(base), *map(pa.array, scores)], names=columns)
            rare = np.flatnonzero(~found)
            if len(rare):
                k = len(rare)
                yield pa.RecordBatch.from_arrays([pa.array(row[text[rare]]), pa.nulls(k, pa.int64()), pa.nulls(k, pa.bool_()), pa.array(h[rare]), pa.array(c[rare]), pa.nulls(k, pa.int64()), *[pa.nulls(k, pa.float64())] * (1 + classes)], names=columns)

    parts = written(rows.select("doc_id", "train", "text").mapInArrow(run, "row long, doc_id long, train boolean, h long, n long, known long, base double, " + ", ".join(f"{c} double" for c in names)), "parts")
    rare = values.where(F.col("total") < least).select("h", "seen", *names)
    joined = parts.where("h is not null").select("row", "h", F.col("n").alias("c")).join(rare, "h")
    c = F.col("c")

    def drawn(log_p: Column) -> Column:
        """Log of the urn's factor for c draws of one word."""
        mass = urn * F.exp(log_p)
        more = _log_gamma(mass + c) - _log_gamma(mass + 1)
        return log_p + log_urn + F.when(c > 1, more).otherwise(0.0)

    tails = joined.groupBy("row").agg(F.sum(F.when(F.col("seen") > 0, c).otherwise(0)).alias("t_known"), F.sum(c * (F.log10(F.col("seen") + 1.0) - floor)).alias("t_base"), *[F.sum(drawn(F.col(x))).alias(f"t_{x}") for x in names])
    whole = parts.where("h is null").join(tails, "row", "left")
    both = lambda x: F.col(x) + F.coalesce(F.col(f"t_{x}"), F.lit(0))
    prior = [math.log(max(e, 1e-9) / max(1, all_ends)) if all_ends else -math.log(classes) for e in ends]
    logs = [both(x) + F.lit(q) for x, q in zip(names, prior, strict=True)]
    best = F.greatest(*logs) if classes > 1 else logs[0]
    mixed = best + F.ln(sum((F.exp(x - best) for x in logs), F.lit(0.0)))
    spent = _log_gamma(urn + F.col("n")) - _log_gamma(F.lit(urn))
    return whole.select("doc_id", "train", F.col("n").alias("n_tokens"), both("known").cast("long").alias("n_known"), F.lit(all_tokens).cast("long").alias("train_tokens"), both("base").alias("base_score"), ((mixed - spent) / LOG10).alias("score"))
